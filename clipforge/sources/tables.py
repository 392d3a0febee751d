"""Readers with explicit schemas, and the stand-in views over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import floor_int, int_div, key_int

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def read_files(spark: SparkSession, path: str, kind: str, schema: str, **options) -> DataFrame:
    """Files of any of Spark's kinds (parquet, orc, csv, json, text) under an explicit schema, so nothing is read to guess it.

    A broken row of CSV or JSON ends the read; ``mode`` among the options says otherwise.
    """
    if kind not in ("parquet", "orc", "csv", "json", "text"):
        raise ValueError(f"unknown kind of file {kind}")
    reader = spark.read.options(**({"mode": "FAILFAST"} if kind in ("csv", "json") else {}) | options)
    return reader.schema(schema).format(kind).load(path)


def media_meta(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Container metadata of one media file for each order."""
    o = load(spark, sf_dir, "orders")
    price = floor_int(F.col("o_totalprice"))
    rates = F.create_map(*[F.lit(v) for p in (("1", 48000), ("2", 44100), ("3", 22050), ("4", 16000)) for v in p])
    return o.select(
        F.col("o_orderkey").alias("media_id"),
        (price % 160 + 1).alias("frames"),
        (F.lit(16).cast("bigint") * (F.col("o_custkey") % 60 + 15)).alias("height"),
        (F.lit(16).cast("bigint") * (floor_int(F.col("o_totalprice") / 7) % 100 + 20)).alias("width"),
        (F.dayofyear("o_orderdate").cast("bigint") % 53 + 8).alias("fps"),
        F.coalesce(F.try_element_at(rates, F.substring("o_orderpriority", 1, 1)), F.lit(8000)).cast("bigint").alias("sample_rate"),
        F.col("o_orderstatus").alias("status"))


def frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per frame: the events of a user in time order."""
    e = load(spark, sf_dir, "events")
    order = W.partitionBy("user_id").orderBy("ts", "event_id")
    return e.select(F.col("user_id").alias("media_id"), F.row_number().over(order).cast("bigint").alias("frame_no"), F.col("value").alias("luma"),
                    F.get_json_object("props", "$.k").cast("bigint").alias("texture"), F.col("event_type").alias("kind"), "ts", "event_id")


def frames_planted(spark: SparkSession, sf_dir: str, ramp: bool = False) -> DataFrame:
    """Frames with known cuts: the level steps by 300 every 12 frames, at once or over four frames."""
    f = frames(spark, sf_dir).withColumn("seg", int_div(F.col("frame_no") - 1, 12)).withColumn("pos", (F.col("frame_no") - 1) % 12)
    level = F.lit(300.0) * (F.col("seg") % 2)
    if ramp:
        before = F.lit(300.0) * ((F.col("seg") + 1) % 2)
        level = F.when((F.col("seg") > 0) & (F.col("pos") <= 3), before + (level - before) * (F.col("pos") + 1) / 5).otherwise(level)
    return f.select("media_id", "frame_no", (F.col("luma") + level).alias("luma"), ((F.col("seg") > 0) & (F.col("pos") == 0)).alias("true_cut"))


def clips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scored clips: order lines, grouped because their key repeats."""
    l = load(spark, sf_dir, "lineitem")
    pct = lambda c, k: (F.max(F.round(c * 100).cast("bigint")) * k)
    g = l.groupBy(F.col("l_orderkey").alias("video_id"), F.col("l_linenumber").cast("bigint").alias("clip_no")).agg(
        (floor_int(F.max("l_quantity")) % 160 * 4 + 1).alias("n_frames"),
        (floor_int(F.max("l_extendedprice")) % 100).alias("body"),
        F.max((F.col("l_partkey") + F.col("l_suppkey")) % 100).alias("face"),
        pct(F.col("l_discount"), 9).alias("appeal"),
        pct(F.col("l_tax"), 12).alias("clarity"),
        (floor_int(F.max("l_quantity")) * 2).alias("occlusion"),
        F.min("l_returnflag").alias("flag"))
    return g


SCORES = ("body", "face", "appeal", "clarity", "occlusion")


def text_clips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The lines of every document."""
    d = load(spark, sf_dir, "documents")
    return d.select("doc_id", "lang", "source", F.posexplode(F.split("text", "\n", -1)).alias("clip_no", "line")).select(
        "doc_id", F.col("clip_no").cast("bigint").alias("clip_no"), "line", F.length("line").cast("bigint").alias("len"), "lang", "source")


def turn_clips(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "conversations").select(F.col("conv_id").alias("video_id"), F.col("turn").alias("clip_no"), "role", "text")


def review(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Human verdicts, and votes on four criteria that differ from them now and then."""
    r = load(spark, sf_dir, "labels")
    votes = [F.when(key_int(F.col("doc_id"), str(i)) % 10 == 0, 1 - F.col("quality")).otherwise(F.col("quality")).cast("bigint").alias(f"v{i}") for i in range(1, 5)]
    return r.select("doc_id", F.col("quality").cast("bigint").alias("quality"), F.col("toxic").cast("bigint").alias("toxic"), *votes)


def latents(spark: SparkSession, sf_dir: str, grid: str = "444") -> DataFrame:
    """Embeddings as coordinates: 4 x 4 x 4 (t, y, x) or 8 x 8 (y, x)."""
    e = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("item"), "label", F.posexplode("embedding").alias("i", "v"))
    i, val = F.col("i").cast("bigint"), F.col("v").cast("double").alias("val")
    if grid == "88":
        return e.select("item", i.alias("i"), int_div(i, 8).alias("y"), (i % 8).alias("x"), val)
    return e.select("item", i.alias("i"), int_div(i, 16).alias("t"), (int_div(i, 4) % 4).alias("y"), (i % 4).alias("x"), val)


def telemetry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Phase timings of ranks."""
    e = load(spark, sf_dir, "events")
    names = (("view", "forward"), ("click", "backward"), ("purchase", "update"), ("signup", "data"), ("error", "communication"))
    phase = F.create_map(*[F.lit(v) for p in names for v in p])[F.col("event_type")]
    return e.select("event_id", (F.col("user_id") % 64).alias("rank"), phase.alias("phase"), F.col("value").alias("ms"), F.col("ts").cast("timestamp").alias("ts"))


def topology(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, n, r = (load(spark, sf_dir, t) for t in ("supplier", "nation", "region"))
    # nations and regions are reference tables of 25 and 5 rows
    return s.join(F.broadcast(n), s.s_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select(
        F.col("s_suppkey").alias("node"), F.col("n_nationkey").cast("bigint").alias("rack"), F.col("r_regionkey").cast("bigint").alias("pod"))
