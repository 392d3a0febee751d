"""Latent geometry: shapes, causal pooling, tiles and their blending, patches, masks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from clipforge.functions.exprs import int_div


def latent_shape(t: Column, h: Column, w: Column) -> list[Column]:
    return [(F.lit(1).cast("bigint") + int_div(t - 1, 4)).alias("lt"), int_div(h, 8).alias("lh"), int_div(w, 8).alias("lw")]


def pixel_shape(lt: Column, lh: Column, lw: Column) -> list[Column]:
    return [((lt - 1) * 4 + 1).alias("t"), (lh * 8).alias("h"), (lw * 8).alias("w")]


def group_of(frame_no: Column) -> Column:
    """Frame 1 alone, then groups of four (0, 1, 1, 1, 1, 2, ...)."""
    return F.ceil((frame_no - 1) / 4).cast("bigint")


def causal_pool(frames: DataFrame, key: str = "media_id", order: str = "frame_no", value: str = "luma") -> DataFrame:
    """Mean per group: what comes later than a group never changes it."""
    return frames.groupBy(key, group_of(F.col(order)).alias("g")).agg(F.avg(value).alias("latent"), F.count("*").alias("n"))


def upsample(latents: DataFrame, frames: DataFrame, key: str = "media_id", order: str = "frame_no") -> DataFrame:
    """Each frame with its group's latent."""
    return frames.withColumn("g", group_of(F.col(order))).join(latents.select(key, "g", "latent"), [key, "g"])


def tile_starts(n: int, size: int, overlap: int) -> list[int]:
    """Starts of tiles of ``size`` that overlap; the last is clamped to the end."""
    step, out = size - overlap, [0]
    if step < 1:
        raise ValueError("the overlap must be smaller than the tile")
    while out[-1] + size < n:
        out.append(min(out[-1] + step, n - size))
    return out


def tiles(spark, shape: tuple[int, int, int], size: tuple[int, int, int], overlap: tuple[int, int, int]) -> DataFrame:
    """A tile per row: id and start of each axis."""
    starts = [tile_starts(n, s, o) for n, s, o in zip(shape, size, overlap, strict=True)]
    rows = [(k, *p) for k, p in enumerate((a, b, c) for a in starts[0] for b in starts[1] for c in starts[2])]
    return spark.createDataFrame(rows, "tile bigint, t0 bigint, y0 bigint, x0 bigint")


def covering(c: Column, starts: list[int], size: int) -> Column:
    """Starts of the tiles that cover a coordinate: literals, so no join."""
    return F.filter(F.array(*[F.lit(s).cast("bigint") for s in starts]), lambda s: (s <= c) & (c < s + size))


def ramp(c: Column, start: Column, size: int, overlap: int, n: int) -> Column:
    """Linear weight towards the inside of a tile, full at the borders of the whole."""
    up = F.when(start == 0, 1.0).otherwise(F.least(F.lit(1.0), (c - start + 1) / F.lit(float(overlap + 1))))
    down = F.when(start + size == n, 1.0).otherwise(F.least(F.lit(1.0), (start + size - c) / F.lit(float(overlap + 1))))
    return F.least(up, down)


def cut_tiles(cells: DataFrame, n: int, size: int, overlap: int, ramped: bool = True) -> DataFrame:
    """Cells (item, y, x, val) of an n x n grid, once for each tile that covers them, with a weight."""
    starts = tile_starts(n, size, overlap)
    out = cells.withColumn("y0", F.explode(covering(F.col("y"), starts, size))).withColumn("x0", F.explode(covering(F.col("x"), starts, size)))
    weight = ramp(F.col("y"), F.col("y0"), size, overlap, n) * ramp(F.col("x"), F.col("x0"), size, overlap, n) if ramped else F.lit(1.0)
    return out.withColumn("weight", weight)


def blend(tiled: DataFrame, value: str = "val") -> DataFrame:
    """Weighted mean over tiles: two sums that combine before the shuffle."""
    return tiled.groupBy("item", "y", "x").agg((F.sum(F.col("weight") * F.col(value)) / F.sum("weight")).alias("blended"), F.count("*").alias("cover"))


def assign_tiles(tile_ids: DataFrame, devices: int) -> DataFrame:
    return tile_ids.withColumn("device", F.col("tile") % devices)


def compression_ratio(channels: int) -> float:
    """Pixels of three channels over latent cells of ``channels``."""
    return 3 * 4 * 8 * 8 / channels


def patchify(cells: DataFrame, p: int = 2) -> DataFrame:
    """(item, t, py, px, patch): values of a p x p patch in row order."""
    rows = cells.select("item", "t", int_div(F.col("y"), p).alias("py"), int_div(F.col("x"), p).alias("px"), F.struct(((F.col("y") % p) * p + F.col("x") % p).alias("k"), F.col("val").alias("v")).alias("c"))
    return rows.groupBy("item", "t", "py", "px").agg(F.transform(F.sort_array(F.collect_list("c")), lambda c: c["v"]).alias("patch"))


def unpatchify(tokens: DataFrame, p: int = 2) -> DataFrame:
    rows = tokens.select("item", "t", "py", "px", F.posexplode("patch").alias("k", "val"))
    return rows.select("item", "t", (F.col("py") * p + int_div(F.col("k"), p)).alias("y"), (F.col("px") * p + F.col("k") % p).alias("x"), "val")


def mask_pool(mask: DataFrame) -> DataFrame:
    """A mask reduced in time like the video: the mean of its group, rounded. Frames (item, frame_no, m)."""
    return mask.groupBy("item", group_of(F.col("frame_no")).alias("g")).agg(F.round(F.avg("m")).cast("bigint").alias("pooled"))


def mask_fold(mask: DataFrame) -> DataFrame:
    """A mask folded to four channels per latent frame: nothing is lost. The first frame fills all four."""
    one = mask.filter("frame_no = 1").select("item", F.lit(0).cast("bigint").alias("g"), F.explode(F.array(*[F.lit(k).cast("bigint") for k in range(4)])).alias("channel"), "m")
    rest = mask.filter("frame_no > 1").select("item", group_of(F.col("frame_no")).alias("g"), ((F.col("frame_no") - 2) % 4).alias("channel"), "m")
    return one.unionByName(rest)


def mask_unfold(folded: DataFrame) -> DataFrame:
    first = folded.filter("g = 0 and channel = 0").select("item", F.lit(1).cast("bigint").alias("frame_no"), "m")
    return first.unionByName(folded.filter("g > 0").select("item", ((F.col("g") - 1) * 4 + F.col("channel") + 2).alias("frame_no"), "m"))
