"""Helpers shared by the training-data operators: shared scratch tables, readers, sampling."""

from __future__ import annotations

import ctypes

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from clipforge.sources.scratch import materialize, remove, scratch_path, scratch_scope  # noqa: F401


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def held_out(doc_id: Column) -> Column:
    """True for the fifth of the ids that no classifier may learn from (null counts as the empty text)."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 5 == 0


def shuffle_parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def labelled_sample(docs: DataFrame, labels: DataFrame, target: str, per_class: dict[int, int]) -> DataFrame:
    """Texts and labels of a bounded, keyed sample: at most ``per_class[y]`` ids of each class.

    Held-out ids are left out. Ids are taken in the order of their hash, so
    reruns agree. Where an id repeats, its largest label and its smallest text
    stand for it, so the bound holds however often rows repeat.
    """
    seen = (labels.select(F.col("doc_id"), F.col(target).cast("int").alias("y"))
            .filter("doc_id is not null and y is not null").filter(~held_out(F.col("doc_id")))
            .groupBy("doc_id").agg(F.max("y").alias("y")))
    picks = None
    for y, n in sorted(per_class.items()):
        pick = seen.filter(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n)
        picks = pick if picks is None else picks.unionByName(pick)
    # at most sum(per_class) rows of two numbers: small enough to send to every executor
    chosen = docs.select("doc_id", "text").join(F.broadcast(picks), "doc_id")
    return chosen.groupBy("doc_id", "y").agg(F.min(F.coalesce("text", F.lit(""))).alias("text"))


_HELD: dict = {}


def held(kind: str, what, make):
    """``make(what)``, kept by a Python worker until it is asked for something else, so at most one model is in memory."""
    key = (kind, hash(what if isinstance(what, (bytes, str)) else tuple(what)))
    if key not in _HELD:
        _HELD.clear()
        _HELD[key] = make(what)
    return _HELD[key]


def give_back() -> None:
    """Gives free memory back to the system; a worker lives on between tasks and would keep it."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # not glibc
        pass


def released(batches):
    """The batches; what they took is given back after every few and after the last."""
    n = 0
    for n, batch in enumerate(batches):
        yield batch
        del batch
        if n % 8 == 7:
            give_back()
    give_back()


def train_once(sample: DataFrame, fit, name: str) -> bytes:
    """Runs ``fit(list of texts, list of labels) -> bytes`` in one task over a bounded sample."""
    def run(batches):
        texts, ys = [], []
        for pdf in batches:
            texts += pdf["text"].tolist()
            ys += pdf["y"].tolist()
            ids_ = pdf["doc_id"].tolist()
            order.extend(ids_)
        import pandas as pd
        rank = sorted(range(len(order)), key=order.__getitem__)
        yield pd.DataFrame({"model": [fit([texts[i] for i in rank], [int(ys[i]) for i in rank])]})

    order: list[int] = []
    rows = sample.select("doc_id", "y", "text").coalesce(1).mapInPandas(run, "model binary").collect()
    return bytes(rows[0]["model"]) if rows else fit([], [])


FILTER_BITS = 1 << 26


def marked_likely(rows: DataFrame, key: Column, members: DataFrame, member: Column, name: str, bits: int = FILTER_BITS) -> DataFrame:
    """Adds ``name``: whether the hash ``key`` may be among ``members``; true for all that are, and a few more.

    The members' hashes set bits of one bitmap of ``bits`` bits, kept as rows of
    4 KB. It is broadcast whole: 8 MB at most, however many members there are, so
    a join that follows moves little besides what it keeps.
    """
    place = lambda c: F.pmod(c, F.lit(bits))
    page = 1 << 15
    put = members.select(place(member).alias("p_"))
    pages = put.groupBy(F.floor(F.col("p_") / page).cast("int").alias("page_")).agg(F.bitmap_construct_agg(F.col("p_") % page).alias("bits_"))
    at = rows.withColumn("p_", place(key)).withColumn("page_", F.floor(F.col("p_") / page).cast("int"))
    byte = F.conv(F.hex(F.substring(F.col("bits_"), (F.floor((F.col("p_") % page) / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    hit = F.coalesce(F.expr("shiftright(b_, cast(p_ % 8 as int)) & 1") == 1, F.lit(False))
    return at.join(F.broadcast(pages), "page_", "left").withColumn("b_", byte).withColumn(name, hit).select(*rows.columns, name)


def only_likely(rows: DataFrame, key: Column, members: DataFrame, member: Column) -> DataFrame:
    """The rows that ``marked_likely`` marks."""
    return marked_likely(rows, key, members, member, "likely_").filter("likely_").drop("likely_")
