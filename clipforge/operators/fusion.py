"""Window-fused denoising of long tracks, masks, fillers and the whole inpainting flow.

Tracks are rows (item, i, val), i from 0. The relational form takes one shuffle
for each step; ``fused_denoise_grouped`` holds one item's track in a task (at
most 10**5 values) and takes one shuffle in all.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import gauss, key_int


def window_starts(total: int, n: int, s: int) -> list[int]:
    """Starts of windows of ``n`` by ``s``; the last is clamped to the end. A track no longer than a window is one window."""
    if s > n or s < 1:
        raise ValueError("the stride must be between 1 and the window")
    if total <= n:
        return [0]
    count = -(-(total - n) // s) + 1
    return [min(k * s, total - n) for k in range(count)]


def starts_of(total: Column, n: int, s: int) -> Column:
    """window_starts as an expression."""
    count = F.when(total <= n, 1).otherwise(F.ceil((total - n) / s) + 1).cast("int")
    return F.transform(F.sequence(F.lit(0), count - 1), lambda k: F.greatest(F.lit(0).cast("bigint"), F.least((k * s).cast("bigint"), (total - n).cast("bigint"))))


def fusion_windows(tracks: DataFrame, n: int, s: int) -> DataFrame:
    """(item, clip, start, size) for tracks given as (item, total)."""
    if s > n or s < 1:
        raise ValueError("the stride must be between 1 and the window")
    return tracks.select("item", "total", F.posexplode(starts_of(F.col("total"), n, s)).alias("clip", "start")).select("item", F.col("clip").cast("bigint").alias("clip"), "start", F.least(F.lit(n).cast("bigint"), "total").alias("size"))


def with_total(track: DataFrame) -> DataFrame:
    return track.withColumn("total", F.count("*").over(W.partitionBy("item")))


def members(track: DataFrame, n: int, s: int) -> DataFrame:
    """Each value once for every window that covers it: (item, i, val, start)."""
    size = F.least(F.lit(n).cast("bigint"), F.col("total"))
    covering = F.filter(F.array_distinct(starts_of(F.col("total"), n, s)), lambda a: (a <= F.col("i")) & (F.col("i") < a + size))
    return with_total(track).withColumn("start", F.explode(covering)).drop("total")


def smooth(parts: DataFrame, keep: float = 0.5) -> DataFrame:
    """A stand-in for one denoising step: each value drawn towards the mean of itself and its neighbours in the window."""
    w = W.partitionBy("item", "start").orderBy("i").rowsBetween(-1, 1)
    return parts.withColumn("val", F.lit(keep) * F.col("val") + F.lit(1 - keep) * F.avg("val").over(w))


def fuse(parts: DataFrame) -> DataFrame:
    """The mean over windows: sums and counts combine before the shuffle."""
    return parts.groupBy("item", "i").agg(F.avg("val").alias("val"))


def fused_denoise(track: DataFrame, steps: int, n: int, s: int, step: Callable[[DataFrame], DataFrame] = smooth) -> DataFrame:
    for _ in range(steps):
        track = fuse(step(members(track, n, s)))
    return track


def fused_denoise_grouped(track: DataFrame, steps: int, n: int, s: int, keep: float = 0.5) -> DataFrame:
    """The same with one item's track per call."""
    import numpy as np

    def run(pdf):
        pdf = pdf.sort_values("i")
        v = pdf["val"].to_numpy(float)
        for _ in range(steps):
            total, count = np.zeros_like(v), np.zeros_like(v)
            for a in dict.fromkeys(window_starts(len(v), n, s)):
                part = v[a:a + n]
                near = np.convolve(part, np.ones(3), "same") / np.convolve(np.ones(len(part)), np.ones(3), "same")
                total[a:a + n] += keep * part + (1 - keep) * near
                count[a:a + n] += 1
            v = total / count
        return pdf.assign(val=v)

    return track.select("item", "i", "val").groupBy("item").applyInPandas(run, "item long, i long, val double")


def concat_clips(track: DataFrame, steps: int, n: int) -> DataFrame:
    """The baseline: windows side by side, each denoised alone."""
    parts = track.withColumn("start", F.col("i") - F.col("i") % n)
    for _ in range(steps):
        parts = smooth(parts)
    return parts.select("item", "i", "val")


def seam_jump(track: DataFrame, n: int) -> DataFrame:
    """Mean absolute step at the places where windows of ``n`` meet."""
    step = F.abs(F.col("val") - F.lag("val").over(W.partitionBy("item").orderBy("i")))
    return track.withColumn("step", step).filter((F.col("i") % n == 0) & (F.col("i") > 0)).agg(F.count("*").alias("seams"), F.avg("step").alias("jump"))


# --- masks ---------------------------------------------------------------------------------------

def stationary_mask(cells: DataFrame, size: int = 3, grid: int = 8) -> DataFrame:
    """Adds ``m``: a keyed square of each item."""
    y0, x0 = (key_int(F.col("item"), k) % (grid - size + 1) for k in ("my", "mx"))
    return cells.withColumn("m", (F.col("y").between(y0, y0 + size - 1) & F.col("x").between(x0, x0 + size - 1)).cast("bigint"))


def moving_mask(cells: DataFrame, size: int = 2, grid: int = 4) -> DataFrame:
    """Adds ``m``: a keyed square that moves with time and is thrown back at the borders."""
    span = grid - size
    def at(k: str) -> Column:
        p = (key_int(F.col("item"), k) + F.col("t") * (key_int(F.col("item"), k, "v") % 2 + 1)) % (2 * span)
        return F.when(p <= span, p).otherwise(2 * span - p)

    y0, x0 = at("my"), at("mx")
    return cells.withColumn("m", (F.col("y").between(y0, y0 + size - 1) & F.col("x").between(x0, x0 + size - 1)).cast("bigint"))


def band_mask(cells: DataFrame, grid: int = 8) -> DataFrame:
    """Adds ``m``: the bottom quarter, where captions stand."""
    return cells.withColumn("m", (F.col("y") >= grid - grid // 4).cast("bigint"))


def track_mask(track: DataFrame, length: int = 5, every: int = 16) -> DataFrame:
    """Adds ``m`` to a track: ``length`` keyed places out of ``every``."""
    return track.withColumn("m", ((F.col("i") + key_int(F.col("item"), "tm")) % every < length).cast("bigint"))


# --- fillers -------------------------------------------------------------------------------------

def _sides() -> tuple[Column, Column, Column, Column]:
    w = W.partitionBy("item").orderBy("i")
    known, place = F.when(F.col("m") == 0, F.col("val")), F.when(F.col("m") == 0, F.col("i"))
    back, ahead = w.rowsBetween(W.unboundedPreceding, 0), w.rowsBetween(0, W.unboundedFollowing)
    return F.last(known, True).over(back), F.last(place, True).over(back), F.first(known, True).over(ahead), F.first(place, True).over(ahead)


def fill_propagate(track: DataFrame) -> DataFrame:
    """Masked values from the nearest known one along time, the earlier on ties: the flow-guided baseline with motion zero."""
    a, ia, b, ib = _sides()
    nearer = F.when(a.isNull(), b).when(b.isNull(), a).when(F.col("i") - ia <= ib - F.col("i"), a).otherwise(b)
    return track.withColumn("filled", F.when(F.col("m") == 0, F.col("val")).otherwise(F.coalesce(nearer, F.lit(0.0))))


def fill_linear(track: DataFrame) -> DataFrame:
    """Masked values on the line between the known ones on either side."""
    a, ia, b, ib = _sides()
    line = F.when(a.isNull(), b).when(b.isNull(), a).otherwise(a + (b - a) * (F.col("i") - ia) / F.greatest(ib - ia, F.lit(1).cast("bigint")))
    return track.withColumn("filled", F.when(F.col("m") == 0, F.col("val")).otherwise(F.coalesce(line, F.lit(0.0))))


def fill_mean(track: DataFrame) -> DataFrame:
    mean = F.avg(F.when(F.col("m") == 0, F.col("val"))).over(W.partitionBy("item"))
    return track.withColumn("filled", F.when(F.col("m") == 0, F.col("val")).otherwise(F.coalesce(mean, F.lit(0.0))))


# --- the whole completion flow -------------------------------------------------------------------
# Videos are rows (item, i, y, x, val) of a grid x grid picture, i from 0; m is 1 where a pixel is hidden.

CELL = 2  # pixels of a latent cell along y and x; along time the first frame stands alone, then groups of four


def latent_place(i: Column) -> Column:
    """The latent frame of a frame counted from 0."""
    return F.ceil(i / 4).cast("bigint")


def encode_masked(video: DataFrame, grid: int) -> DataFrame:
    """(item, g, c, y1, folds): the latent of what is seen (null where nothing is), and the mask folded to four channels.

    Folding keeps for each latent cell how much of it each of its frames hides, so
    no time is lost; the first frame fills all four channels.
    """
    side = grid // CELL
    cells = video.select("item", latent_place(F.col("i")).alias("g"), (F.floor(F.col("y") / CELL) * side + F.floor(F.col("x") / CELL)).cast("bigint").alias("c"), ((F.col("i") + 3) % 4).alias("k"), F.col("i"), "val", "m")
    hidden = lambda k: F.avg(F.when((F.col("k") == k) | (F.col("i") == 0), F.col("m")))
    return cells.groupBy("item", "g", "c").agg(F.avg(F.when(F.col("m") == 0, F.col("val"))).alias("y1"), *[F.coalesce(hidden(k), F.lit(1.0)).alias(f"f{k}") for k in range(4)])


def condition_latents(latents: DataFrame) -> DataFrame:
    """Adds seen (share of the cell that is not hidden), ctx (its latent, else one from the line along time, else from the cells beside it) and eps, keyed noise."""
    w = W.partitionBy("item", "c").orderBy("g")
    back, ahead = w.rowsBetween(W.unboundedPreceding, 0), w.rowsBetween(0, W.unboundedFollowing)
    place = F.when(F.col("y1").isNotNull(), F.col("g"))
    rows = latents.withColumns({"va": F.last("y1", True).over(back), "ga": F.last(place, True).over(back), "vb": F.first("y1", True).over(ahead), "gb": F.first(place, True).over(ahead)})
    line = F.when(F.col("va").isNull(), F.col("vb")).when(F.col("vb").isNull(), F.col("va")).otherwise(F.col("va") + (F.col("vb") - F.col("va")) * (F.col("g") - F.col("ga")) / F.greatest(F.col("gb") - F.col("ga"), F.lit(1).cast("bigint")))
    beside = F.avg("line").over(W.partitionBy("item", "g"))
    rows = rows.withColumn("line", line).withColumn("ctx", F.coalesce("line", beside, F.lit(0.0)))
    seen = F.lit(1.0) - sum((F.col(f"f{k}") for k in range(4)), F.lit(0.0)) / 4
    return rows.select("item", "c", F.col("g").alias("i"), "ctx", seen.alias("seen"), gauss(F.col("item"), "_", F.col("g"), "_", F.col("c")).alias("eps"))


def token_inputs(conditioned: DataFrame) -> DataFrame:
    """(item, i, token): latents, folded masks and noise, cut into 2 x 2 patches and added: a third of the tokens that joining them would take."""
    one = F.transform(F.sort_array(F.collect_list(F.struct("c", (F.col("ctx") + F.col("seen") + F.col("eps")).alias("v")))), lambda x: x["v"])
    return conditioned.groupBy("item", "i").agg(one.alias("token"))


def flow_step(parts: DataFrame, step: int, steps: int) -> DataFrame:
    """One Euler step in every window. A stand-in without weights predicts the data from what a cell's context says and from what its neighbours in time have come to."""
    t = step / steps
    w = W.partitionBy("item", "c", "start").orderBy("i").rowsBetween(-1, 1)
    reached = F.col("val") + (1 - t) * (F.col("ctx") - F.col("eps"))
    keep = 0.5 + 0.5 * F.col("seen")
    predicted = keep * F.col("ctx") + (1 - keep) * F.avg(reached).over(w)
    return parts.withColumn("val", F.col("val") + (predicted - F.col("eps")) / steps)


def flow_latents(conditioned: DataFrame, steps: int, n: int = 8, s: int = 4) -> DataFrame:
    """Noise carried to data in ``steps`` steps: every window takes its own step, overlapping results are averaged, and the next step starts from them."""
    x = conditioned.withColumn("val", F.col("eps"))
    total = F.count("*").over(W.partitionBy("item", "c"))
    size = F.least(F.lit(n).cast("bigint"), F.col("total"))
    covering = F.filter(F.array_distinct(starts_of(F.col("total"), n, s)), lambda a: (a <= F.col("i")) & (F.col("i") < a + size))
    x = x.withColumn("total", total).withColumn("starts", covering).drop("total")
    for k in range(steps):
        parts = flow_step(x.withColumn("start", F.explode("starts")), k, steps)
        x = parts.groupBy("item", "c", "i").agg(F.avg("val").alias("val"), *[F.any_value(c).alias(c) for c in ("ctx", "seen", "eps", "starts")])
    return x.select("item", "c", F.col("i").alias("g"), "val")


def inpaint(video: DataFrame, steps: int, grid: int = 4, n: int = 8, s: int = 4) -> DataFrame:
    """The completed video: encode what is seen, fold the mask, denoise in fused windows, decode, and keep every pixel that was seen. Adds ``filled``."""
    side = grid // CELL
    made = flow_latents(condition_latents(encode_masked(video, grid)), steps, n, s).withColumnRenamed("val", "made")
    keyed = video.withColumns({"g": latent_place(F.col("i")), "c": (F.floor(F.col("y") / CELL) * side + F.floor(F.col("x") / CELL)).cast("bigint")})
    return keyed.join(made, ["item", "g", "c"]).withColumn("filled", F.when(F.col("m") == 0, F.col("val")).otherwise(F.col("made"))).drop("made", "g", "c")


def fill_pixels(video: DataFrame, fill: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """A filler of tracks applied to every pixel's track; what no frame of a track shows comes from the seen pixels of its frame. Adds ``filled``."""
    row = F.struct("item", "y", "x")
    tracks = fill(video.withColumn("pixel", row).withColumnRenamed("item", "item_").withColumn("item", F.col("pixel")))
    never = F.min("m").over(W.partitionBy("pixel")) == 1
    beside = F.avg(F.when(F.col("m") == 0, F.col("val"))).over(W.partitionBy("item_", "i"))
    out = tracks.withColumn("filled", F.when(never, F.coalesce(beside, F.lit(0.0))).otherwise(F.col("filled")))
    return out.drop("item", "pixel").withColumnRenamed("item_", "item")


def inpaint_tokens(w: Column, h: Column, n: Column) -> Column:
    """Tokens of summed inputs; concatenated inputs take three times as many."""
    return F.floor(w * h * n / 4).cast("bigint")
