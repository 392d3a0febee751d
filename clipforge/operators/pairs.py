"""Identity pairs for personalisation, and ways to feed the reference."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from clipforge.functions.exprs import key_int
from clipforge.operators.dedup import near_in_blocks, near_sums_in_blocks


def single_subject(clips: DataFrame, subjects: Column) -> DataFrame:
    return clips.filter(subjects == 1)


def intra_pairs(frames: DataFrame, clip: str, frame: str, seed: str = "ref") -> DataFrame:
    """(clip, ref_frame): one keyed frame of each clip is its own reference."""
    pick = F.min_by(frame, F.struct(key_int(F.col(clip), "_", F.col(frame), seed), F.col(frame)))
    return frames.groupBy(clip).agg(pick.alias("ref_frame"), F.count("*").alias("n_frames"))


def cross_pairs(clips: DataFrame, video: str, clip: str, sim, t: float) -> DataFrame:
    """Unordered pairs of clips of one video whose similarity exceeds ``t``: an equi-join on the video. ``sim`` takes the two sides' feature columns."""
    l = clips.select(video, F.col(clip).alias("a"), F.col("feature").alias("fa"))
    r = clips.select(video, F.col(clip).alias("b"), F.col("feature").alias("fb"))
    return l.join(r, video).filter("a < b").withColumn("sim", sim(F.col("fa"), F.col("fb"))).filter(F.col("sim") > t).select(video, "a", "b", "sim")


def cross_vectors(clips: DataFrame, group: str, clip: str, t: float) -> DataFrame:
    """``cross_pairs`` of vectors by their rounded cosine, where a group may hold a large part of all clips: it meets block by block."""
    rows = clips.select(group, F.col(clip).alias("k"), F.col("feature").alias("v"))
    return near_in_blocks(rows, [group], t, cosine=True)


def cross_vector_sums(clips: DataFrame, group: str, clip: str, t: float) -> DataFrame:
    """(group, n, total, best) of the pairs of ``cross_vectors``, which themselves stay in their tasks."""
    rows = clips.select(group, F.col(clip).alias("k"), F.col("feature").alias("v"))
    return near_sums_in_blocks(rows, [group], t, cosine=True)


def set_jaccard(a: Column, b: Column) -> Column:
    common = F.size(F.array_intersect(a, b))
    return F.when(F.size(a) + F.size(b) > 0, common / (F.size(a) + F.size(b) - common)).otherwise(0.0)


def pair_curriculum(intra: DataFrame, cross: DataFrame, key: str, share: float, seed: str = "mix") -> DataFrame:
    """All intra pairs, and the keyed ``share`` of cross pairs."""
    picked = cross.filter(key_int(F.col(key), seed).cast("double") < F.lit(share * 2**32))
    return intra.select(key, F.lit("intra").alias("kind")).unionByName(picked.select(key, F.lit("cross").alias("kind")))


def copy_rate(pairs: DataFrame, near: float = 0.99) -> DataFrame:
    """Share of pairs whose reference is nearly the target itself."""
    return pairs.agg(F.count("*").alias("n"), F.count_if(F.col("sim") >= near).alias("copies"))


def concat_sequence(video: DataFrame, image: DataFrame) -> DataFrame:
    """The reference as one more time slice behind the video's. Cells are (item, t, y, x, val)."""
    last = video.groupBy("item").agg((F.max("t") + 1).alias("t"))
    return video.withColumn("is_ref", F.lit(0)).unionByName(image.join(last, "item").select("item", "t", "y", "x", "val", F.lit(1).alias("is_ref")))


def video_part(cells: DataFrame) -> DataFrame:
    return cells.filter("is_ref = 0").drop("is_ref")


def concat_channels(video: DataFrame, image: DataFrame) -> DataFrame:
    """The reference as a second channel of every cell."""
    return video.join(image.select("item", "y", "x", F.col("val").alias("ref_val")), ["item", "y", "x"], "left")
