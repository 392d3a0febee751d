"""Inference acceleration: step caches, evaluation counts, scaling."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import cosine, key_int, rnd


LAYERS, WIDTH, STEPS, WARMUP = 8, 4, 50, 10  # of the stand-in trace; no step of the warm-up is ever cached
ATTENTION_SHARE = 0.6  # of a layer's work


def refreshed(step: Column, interval: Column, warmup: Column | int = WARMUP) -> Column:
    """Steps that compute everything: the warm-up, then every ``interval``-th."""
    return (step < warmup) | ((step - warmup) % interval == 0)


def cached(trace: DataFrame, key: list[str], value: str, interval: Column, warmup: Column | int = WARMUP) -> DataFrame:
    """Adds ``reused``: the value of the last refreshed step."""
    w = W.partitionBy(*key).orderBy("step").rowsBetween(W.unboundedPreceding, 0)
    return trace.withColumn("reused", F.last(F.when(refreshed(F.col("step"), interval, warmup), F.col(value)), ignorenulls=True).over(w))


def sample_prompts(prompts: DataFrame, n: int = 20, key: str = "item_id") -> DataFrame:
    """A keyed random sample of ``n`` prompts."""
    return prompts.select(key).distinct().orderBy(key_int(F.col(key), "v"), key).limit(n)


def layered_trace(prompts: DataFrame) -> DataFrame:
    """(item_id, layer, j, step, att, ffn): what attention and the rest of each layer add to the features at each step.

    A smooth keyed stand-in without weights: every layer has its own draws and its
    own pace, moves most in the first steps, and attention moves faster than the rest.
    """
    whole = lambda n: F.sequence(F.lit(0).cast("bigint"), F.lit(n - 1).cast("bigint"))
    rows = prompts.withColumn("layer", F.explode(whole(LAYERS))).withColumn("j", F.explode(whole(WIDTH)))
    u = lambda k: key_int(F.col("item_id"), "_", F.col("layer"), "_", F.col("j"), k) / F.lit(float(2**32))
    rows = rows.withColumns({k: u(k) for k in "abcd"}).withColumn("step", F.explode(whole(STEPS)))
    s, layer, j = F.col("step"), F.col("layer"), F.col("j")
    att = F.col("a") * F.exp(-s / (4.0 + layer)) + F.col("b") * F.cos(s / (5.0 + layer) + j) / 4
    ffn = F.col("c") * F.exp(-s / (8.0 + layer)) + F.col("d") * F.sin(s / (12.0 + layer) + j) / 8
    return rows.select("item_id", "layer", "j", "step", att.alias("att"), ffn.alias("ffn"))


def rear_offsets(trace: DataFrame, fronts: list[int]) -> DataFrame:
    """(item_id, front, j, step, layer, attention): what the layers after the first ``front`` add, as a whole and by attention alone."""
    each = trace.withColumn("front", F.explode(F.array(*[F.lit(f).cast("bigint") for f in fronts]))).filter("layer >= front")
    return each.groupBy("item_id", "front", "j", "step").agg(F.sum(F.col("att") + F.col("ffn")).alias("layer"), F.sum("att").alias("attention"))


def cache_configurations(spark, fronts=(2, 3, 4, 5, 6), intervals=(2, 3, 4, 5), starts=(10, 15, 20)) -> DataFrame:
    """All settings: what is cached, after how many layers, how often it is refreshed, from which step on (tens of rows)."""
    rows = [(k, f, i, s) for k in ("layer", "attention") for f in fronts for i in intervals for s in starts]
    return spark.createDataFrame(rows, "kind string, front bigint, iv bigint, start bigint")


def cache_deviation(trace: DataFrame, configurations: DataFrame) -> DataFrame:
    """(item_id, configuration, deviation): mean over steps of the squared distance between output with and without the cache.

    Front layers are always fresh, so what differs is the cached part: of an
    offset over the front's output, or of the rear layers' attention.
    """
    fronts = [r["front"] for r in configurations.select("front").distinct().collect()]
    part = rear_offsets(trace, sorted(fronts)).join(F.broadcast(configurations), "front")
    part = part.withColumn("own", F.when(F.col("kind") == "layer", F.col("layer")).otherwise(F.col("attention")))
    names = ["kind", "front", "iv", "start"]
    part = cached(part, ["item_id", "j", *names], "own", F.col("iv"), F.col("start"))
    off = (F.col("own") - F.col("reused")) * (F.col("own") - F.col("reused"))
    return part.groupBy("item_id", *names).agg((F.sum(off) / STEPS).alias("deviation"))


def configuration_speedup(kind: Column, front: Column, interval: Column, start: Column) -> Column:
    """Layers computed without a cache over those with it: cached steps skip the rear layers, or only their attention."""
    full = evaluations(STEPS, interval, start)
    rear = F.lit(LAYERS) - front
    saved = F.when(kind == "layer", rear).otherwise(rear * ATTENTION_SHARE)
    return F.lit(float(STEPS * LAYERS)) / (F.lit(STEPS * LAYERS) - (F.lit(STEPS) - full) * saved)


def search_cache(deviations: DataFrame) -> DataFrame:
    """Per kind and band of a tenth of speed-up the setting of least mean deviation, with its spread over prompts."""
    names = ["kind", "front", "iv", "start"]
    mean = deviations.groupBy(*names).agg(F.avg("deviation").alias("deviation"), F.stddev_pop("deviation").alias("spread"))
    mean = mean.withColumn("speedup", rnd(configuration_speedup(*[F.col(c) for c in names]) + 1e-9, 4)).withColumn("band", F.floor(F.col("speedup") * 10).cast("bigint"))
    mean = mean.withColumns({"deviation": rnd(F.col("deviation") + 1e-12, 7), "spread": rnd(F.col("spread") + 1e-12, 6)})
    best = F.min(F.struct("deviation", "front", "iv", "start", "speedup", "spread")).alias("b")
    return mean.groupBy("kind", "band").agg(best).select("kind", "band", "b.front", "b.iv", "b.start", "b.speedup", "b.deviation", "b.spread")


def step_similarity(trace: DataFrame, key: str, vec: str) -> DataFrame:
    """Cosine of a vector with that of the step before."""
    before = F.lag(vec).over(W.partitionBy(key).orderBy("step"))
    return trace.withColumn("similarity", cosine(F.col(vec), before)).filter(F.col("similarity").isNotNull())


def evaluations(steps: Column | int, interval: Column, warmup: Column | int = WARMUP) -> Column:
    """Steps of a request that compute everything; one shorter than the warm-up computes all of its steps."""
    steps, warmup = (F.lit(x) if isinstance(x, int) else x for x in (steps, warmup))
    return F.least(steps, warmup) + F.ceil(F.greatest(steps - warmup, F.lit(0)) / interval)


def cache_speedup(steps: Column | int, full: Column, share: Column) -> Column:
    """Units without a cache over units with one, where the steps that are not ``full`` skip ``share`` of the layers."""
    steps = F.lit(steps) if isinstance(steps, int) else steps
    return steps.cast("double") / (full + (steps - full) * (1 - share))


def nfe(steps: Column, guided: Column) -> Column:
    return steps * F.when(guided, 2).otherwise(1)


def scaling_linearity(rows: DataFrame, devices: str, latency: str) -> DataFrame:
    """Speed-up over one device, and its share of the ideal; a row per device count."""
    one = F.first(latency).over(W.orderBy(devices).rowsBetween(W.unboundedPreceding, W.unboundedFollowing))
    out = rows.withColumn("speedup", one / F.col(latency))
    return out.withColumn("linearity", F.col("speedup") / F.col(devices))


def sharded_latency(work: DataFrame, weight: Column, key: Column, devices: list[int], per_node: int = 8, exchange: float = 0.01) -> DataFrame:
    """(devices, shards, replicas, latency): work dealt by key to the devices of a node; nodes beyond the first are replicas.

    The slowest shard decides; each doubling of shards adds an exchange of
    ``exchange`` of the mean work of a request's whole.
    """
    spark = work.sparkSession
    table = spark.createDataFrame([(d, min(d, per_node), max(1, d // per_node)) for d in devices], "devices bigint, shards bigint, replicas bigint")
    load = work.select(key.alias("k"), weight.alias("w")).crossJoin(F.broadcast(table)).groupBy("devices", "shards", "replicas", (F.col("k") % F.col("shards")).alias("shard")).agg(F.sum("w").alias("w"))
    whole = load.groupBy("devices", "shards", "replicas").agg(F.max("w").cast("double").alias("slowest"), F.sum("w").cast("double").alias("all"))
    return whole.select("devices", "shards", "replicas", (F.col("slowest") + F.col("all") * exchange * F.log2("shards")).alias("latency"))
