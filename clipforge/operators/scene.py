"""Shot splitting, cropping and motion over frame rows (media_id, frame_no, luma)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import int_div
from clipforge.operators.quality import quantile

KEY, ORDER = "media_id", "frame_no"


def _w():
    return W.partitionBy(KEY).orderBy(ORDER)


def split_by_delta(frames: DataFrame, t: float, value: str = "luma") -> DataFrame:
    """Adds ``cut``: the step from the frame before is larger than ``t``."""
    return frames.withColumn("cut", F.coalesce(F.abs(F.col(value) - F.lag(value).over(_w())) > t, F.lit(False)))


def split_gradual(frames: DataFrame, t: float, half: int = 3, value: str = "luma") -> DataFrame:
    """Adds ``cut``: means of ``half`` frames before and from here differ by more than ``t``, at a local maximum."""
    before, here = F.avg(value).over(_w().rowsBetween(-half, -1)), F.avg(value).over(_w().rowsBetween(0, half - 1))
    full = (F.count(value).over(_w().rowsBetween(-half, -1)) == half) & (F.count(value).over(_w().rowsBetween(0, half - 1)) == half)
    rows = frames.withColumn("jump", F.when(full, F.round(F.abs(here - before), 9)).otherwise(0.0))
    peak = (F.col("jump") >= F.coalesce(F.lag("jump").over(_w()), F.lit(0.0))) & (F.col("jump") > F.coalesce(F.lead("jump").over(_w()), F.lit(0.0)))
    return rows.withColumn("cut", (F.col("jump") > t) & peak).drop("jump")


def suppress_flash(cuts: DataFrame, r: int = 2, tol: float = 60.0, value: str = "luma") -> DataFrame:
    """Takes back cuts whose level returns within ``r`` frames to that before them, and the cut of the return."""
    w = _w()
    back = F.lit(False)
    for k in range(1, r + 1):
        back = back | F.coalesce(F.abs(F.lead(value, k).over(w) - F.lag(value).over(w)) <= tol, F.lit(False))
    rows = cuts.withColumn("flash_", F.col("cut") & back)
    near = F.max(F.col("flash_").cast("int")).over(w.rowsBetween(-r, 0)) == 1
    return rows.withColumn("cut", F.col("cut") & ~near).drop("flash_")


def split_by_model(frames: DataFrame, score: Callable, t: float, halo: int = 4, chunk: int = 256, value: str = "luma") -> DataFrame:
    """Cuts by any scorer over windows: ``score(values) -> probabilities``.

    Videos go in chunks of ``chunk`` frames with ``halo`` frames on either side,
    so a task never holds a whole long video.
    """
    import pandas as pd

    c = int_div(F.col(ORDER) - 1, chunk)
    places = F.array_distinct(F.array(int_div(F.greatest(F.col(ORDER) - 1 - halo, F.lit(0)), chunk), c, int_div(F.col(ORDER) - 1 + halo, chunk)))
    rows = frames.select(KEY, ORDER, F.col(value).alias("v"), c.alias("own"), F.explode(places).alias("chunk"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(ORDER)
        pdf["cut"] = score(pdf["v"].to_numpy()) > t
        return pdf[pdf["own"] == pdf["chunk"]][[KEY, ORDER, "cut"]]

    return rows.groupBy(KEY, "chunk").applyInPandas(run, f"{KEY} long, {ORDER} long, cut boolean")


def split_by_gap(frames: DataFrame, seconds: int) -> DataFrame:
    """Adds ``cut``: more time than ``seconds`` has passed since the frame before."""
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    return frames.withColumn("cut", F.coalesce(at - F.lag(at).over(_w()) > seconds * 1_000_000, F.lit(False)))


def with_clip_no(cuts: DataFrame) -> DataFrame:
    return cuts.withColumn("clip_no", F.sum(F.col("cut").cast("bigint")).over(_w().rowsBetween(W.unboundedPreceding, 0)))


def clips_from_cuts(cuts: DataFrame, min_frames: int = 3) -> DataFrame:
    out = with_clip_no(cuts).groupBy(KEY, "clip_no").agg(F.min(ORDER).alias("start_frame"), F.max(ORDER).alias("end_frame"), F.count("*").alias("n_frames"))
    return out.filter(F.col("n_frames") >= min_frames)


def boundary_f1(pred: DataFrame, truth: DataFrame, tol: int = 3) -> DataFrame:
    """Precision, recall and F1 of cut places (media_id, frame_no): a cut is matched by any of the other side within ``tol`` frames.

    A banded equi-join: places meet in cells of ``tol`` + 1 frames and their neighbours.
    """
    p = pred.select(KEY, F.col(ORDER).alias("p"), F.explode(F.array(*[int_div(F.col(ORDER), tol + 1) + k for k in (-1, 0, 1)])).alias("cell"))
    q = truth.select(KEY, F.col(ORDER).alias("q"), int_div(F.col(ORDER), tol + 1).alias("cell"))
    hit = p.join(q, [KEY, "cell"]).filter(F.abs(F.col("p") - F.col("q")) <= tol)
    counts = hit.agg(F.countDistinct(KEY, "p").alias("hit_p"), F.countDistinct(KEY, "q").alias("hit_q"))
    both = counts.crossJoin(pred.agg(F.count("*").alias("n_pred"))).crossJoin(truth.agg(F.count("*").alias("n_true")))  # three rows of totals
    rate = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(0.0)
    both = both.withColumns({"precision": rate("hit_p", "n_pred"), "recall": rate("hit_q", "n_true")})
    total = F.col("precision") + F.col("recall")
    return both.withColumn("f1", F.when(total > 0, 2 * F.col("precision") * F.col("recall") / total).otherwise(0.0))


def border_box(cells: DataFrame, level: float, y: str = "y", x: str = "x", value: str = "val") -> DataFrame:
    """Per item the rectangle of cells whose size exceeds ``level``; an item with none has a null box."""
    bright = F.abs(F.col(value)) > level
    return cells.groupBy("item").agg(*[f(F.when(bright, F.col(c))).alias(f"{c}_{n}") for c in (y, x) for n, f in (("min", F.min), ("max", F.max))])


def crop_text_bands(lines: DataFrame, is_text: Column, band: int = 2, key: str = "doc_id", order: str = "clip_no") -> DataFrame:
    """Drops the lines that ``is_text`` marks among the first and last ``band`` of each document."""
    last = F.max(order).over(W.partitionBy(key))
    return lines.withColumn("last_", last).filter(~(is_text & ((F.col(order) < band) | (F.col(order) > F.col("last_") - band)))).drop("last_")


def crop_blank_border(lines: DataFrame, key: str = "doc_id", order: str = "clip_no", line: str = "line") -> DataFrame:
    """Drops the blank lines before the first and after the last that is not."""
    full = F.when(F.trim(line) != "", F.col(order))
    w = W.partitionBy(key)
    return lines.withColumns({"first_": F.min(full).over(w), "last_": F.max(full).over(w)}).filter(F.col(order).between(F.col("first_"), F.col("last_"))).drop("first_", "last_")


def limit_signs(lines: DataFrame, percent: int, key: str = "doc_id", line: str = "line") -> DataFrame:
    """Drops whole items of which more than ``percent`` in a hundred characters are signs: the stand-in for too much text in the picture."""
    w = W.partitionBy(key)
    signs, size = F.sum(F.regexp_count(F.col(line), F.lit(r"[*$%&#!|]"))).over(w), F.sum(F.length(line)).over(w)
    return lines.withColumn("keep_", signs * 100 <= size * percent).filter("keep_").drop("keep_")


def visible_text(html: Column) -> Column:
    """Text outside scripts, styles and tags."""
    out = F.regexp_replace(html, r"(?s)<script[^>]*>.*?</script>", "")
    out = F.regexp_replace(out, r"(?s)<style[^>]*>.*?</style>", "")
    return F.regexp_replace(out, r"(?s)<[^>]*>", "")


def strip_bands(html: Column) -> Column:
    """The page without its head, navigation and footer."""
    for tag in ("head", "nav", "footer"):
        html = F.regexp_replace(html, rf"(?s)<{tag}>.*?</{tag}>", "")
    return html


def motion_score(frames: DataFrame, value: str = "luma") -> DataFrame:
    """Per video the mean absolute step between frames, and the same for each second."""
    step = F.abs(F.col(value) - F.lag(value).over(_w()))
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    rows = frames.withColumns({"step_": step, "at_": at})
    secs = (F.max("at_") - F.min("at_")) / F.lit(1e6)
    return rows.groupBy(KEY).agg(F.count("*").alias("n"), F.coalesce(F.avg("step_"), F.lit(0.0)).alias("per_frame"), F.when(secs > 0, F.sum("step_") / secs).otherwise(0.0).alias("per_second"))


def motion_band(scores: DataFrame, lo: float = 0.05, hi: float = 0.95, score: str = "per_frame") -> DataFrame:
    """Keeps what lies between two quantiles of the score."""
    low, high = (quantile(scores, F.col(score), q) for q in (lo, hi))
    return scores.filter(F.col(score).between(F.lit(low), F.lit(high)))


def block_flow(cells: DataFrame, radius: int = 1, block: int = 2) -> DataFrame:
    """Block matching between neighbouring time slices of (item, t, y, x, val): the offset of least absolute difference per block.

    Offsets outside the grid are left out; ties go to the smaller move, then y, then x. Offsets are (2 radius + 1)**2 literals.
    """
    span = F.sequence(F.lit(-radius), F.lit(radius))
    here = cells.select("item", "t", "y", "x", F.col("val").alias("a"), int_div(F.col("y"), block).alias("block_y"), int_div(F.col("x"), block).alias("block_x"))
    moved = here.withColumn("dy", F.explode(span)).withColumn("dx", F.explode(span))
    there = cells.select("item", (F.col("t") - 1).alias("t"), F.col("y").alias("y2"), F.col("x").alias("x2"), F.col("val").alias("b"))
    met = moved.withColumns({"y2": F.col("y") + F.col("dy"), "x2": F.col("x") + F.col("dx")}).join(there, ["item", "t", "y2", "x2"])
    sad = met.groupBy("item", "t", "block_y", "block_x", "dy", "dx").agg(F.sum(F.abs(F.col("a") - F.col("b"))).alias("sad"), F.count("*").alias("n")).filter(F.col("n") == block * block)
    best = F.min(F.struct(F.round("sad", 9).alias("sad"), (F.abs("dy") + F.abs("dx")).alias("m"), "dy", "dx")).alias("best")
    return sad.groupBy("item", "t", "block_y", "block_x").agg(best).select("item", "t", "block_y", "block_x", "best.dy", "best.dx", "best.sad")
