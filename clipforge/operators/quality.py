"""Safety, balance, quality gates, agreement with reviewers, refinement and annotation routing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import dot, key_int, norm
from clipforge.sources.scratch import materialize


def safety_gate(df: DataFrame, labels: DataFrame, key: str, flag: str = "toxic", unlabelled: str = "keep") -> DataFrame:
    """Drops what is labelled unsafe; what has no label is kept or dropped."""
    unsafe = labels.filter(F.col(flag) == 1).select(key)
    if unlabelled == "keep":
        return df.join(unsafe, key, "left_anti")
    return df.join(labels.filter(F.col(flag) == 0).select(key).distinct(), key, "left_semi").join(unsafe, key, "left_anti")


def balance_cap(df: DataFrame, cat: list[str], cap: int, key: str, seed: str = "cap") -> DataFrame:
    """At most ``cap`` rows per category, in keyed order."""
    order = W.partitionBy(*cat).orderBy(key_int(F.col(key), seed), key)
    return df.withColumn("rn_", F.row_number().over(order)).filter(F.col("rn_") <= cap).drop("rn_")


def _by_rate(df: DataFrame, cat: str, rates: DataFrame, key: str, seed: str) -> DataFrame:
    """Keeps a keyed share of each category. ``rates`` has a row per category, of which there are few; Spark decides on the join."""
    return df.join(rates, cat).filter(key_int(F.col(key), seed).cast("double") < F.col("rate_") * F.lit(float(2**32))).drop("rate_")


def balance_rate(df: DataFrame, cat: str, cap: int, key: str, seed: str = "rate") -> DataFrame:
    """Each category thinned to about ``cap`` rows by hash: no sort, so it holds at any size."""
    rates = df.groupBy(cat).agg(F.least(F.lit(1.0), F.lit(float(cap)) / F.count("*")).alias("rate_"))
    return _by_rate(df, cat, rates, key, seed)


def balance_targets(df: DataFrame, cat: str, alpha: float, key: str, seed: str = "alpha") -> DataFrame:
    """Shares in proportion to count ** alpha, as many rows as that allows without repeats."""
    n = df.groupBy(cat).agg(F.count("*").alias("n_")).withColumn("p_", F.pow("n_", F.lit(alpha) - 1))
    top = n.agg(F.max("p_").alias("top_"))
    rates = n.join(F.broadcast(top)).select(cat, (F.col("p_") / F.col("top_")).alias("rate_"))  # top is one row
    return _by_rate(df, cat, rates, key, seed)


def quantile(df: DataFrame, value: Column, q: float, bins: int = 4096) -> float | None:
    """The exact quantile (linear between neighbours) by histograms of ever smaller ranges.

    Each pass brings at most ``bins`` rows of a count and two edges to the driver;
    the bin that holds the wanted place is the next range, until it is one value.
    No task sorts or gathers the values.
    """
    v = materialize(df.select(value.cast("double").alias("v")).filter("v is not null and not isnan(v)"), "quantile")
    n, least, most = v.agg(F.count("*"), F.min("v"), F.max("v")).first()
    if not n:
        return None

    known: dict[tuple, list] = {}

    def histogram(lo: float, hi: float) -> list:
        if (lo, hi) not in known:
            width = (hi - lo) / bins
            slot = F.least(F.floor((F.col("v") - F.lit(lo)) / F.lit(width)), F.lit(bins - 1)) if width > 0 else F.col("v")
            part = v.filter(F.col("v").between(lo, hi)).groupBy(slot.alias("slot")).agg(F.count("*").alias("n"), F.min("v").alias("lo"), F.max("v").alias("hi")).collect()
            known[lo, hi] = sorted(part, key=lambda r: r["lo"])
        return known[lo, hi]

    def at(place: int) -> float:
        lo, hi, before = least, most, 0
        while lo < hi:
            for r in histogram(lo, hi):
                if place < before + r["n"]:
                    lo, hi = r["lo"], r["hi"]
                    break
                before += r["n"]
        return lo

    place = q * (n - 1)
    low = int(place)
    return at(low) if place == low else at(low) + (at(low + 1) - at(low)) * (place - low)


def drop_low_tail(df: DataFrame, score: str, q: float) -> DataFrame:
    """Only the low tail goes: a score says little about the middle."""
    cut = quantile(df, F.col(score), q)
    return df.filter(F.col(score) >= F.lit(cut))


def quality_gate(df: DataFrame, dims: dict[str, float], mode: str = "all", least: float = 0.0) -> DataFrame:
    """All dimensions at their thresholds, or a weighted sum at ``least``."""
    if mode == "all":
        keep = F.lit(True)
        for c, t in dims.items():
            keep = keep & (F.col(c) >= t)
        return df.filter(keep)
    return df.filter(sum((F.col(c) * w for c, w in dims.items()), F.lit(0.0)) >= least)


def human_quality_gate(df: DataFrame, scores: tuple[str, ...], least: int) -> DataFrame:
    return df.withColumn("worst", F.least(*scores)).filter(F.col("worst") >= least)


def staged_thresholds(df: DataFrame, stages: DataFrame) -> DataFrame:
    """Rows per stage that meet its threshold. A stage per row; tens of stages."""
    return df.join(F.broadcast(stages), F.col("worst") >= F.col("threshold"))


def assign_clusters(df: DataFrame, centroids: list[list[float]], vec: str = "embedding") -> DataFrame:
    """Adds ``cluster_id`` of the nearest centroid by squared distance; ties to the smaller id. Centroids are literals (K x d of a fixed size)."""
    def distance(c: list[float]) -> Column:
        centre = F.array(*[F.lit(float(x)) for x in c])
        return F.aggregate(F.zip_with(F.col(vec), centre, lambda a, b: (a.cast("double") - b) * (a.cast("double") - b)), F.lit(0.0), lambda s, x: s + x)

    options = F.array(*[F.struct(F.round(distance(c), 9).alias("d"), F.lit(i).cast("bigint").alias("id")) for i, c in enumerate(centroids)])
    return df.withColumn("cluster_id", F.array_min(options)["id"])


def lloyd(df: DataFrame, centroids: list[list[float]], rounds: int, vec: str = "embedding") -> list[list[float]]:
    """K-means by aggregation: each round brings K x d means to the driver, rounded so that the order of summation does not show."""
    dim = len(centroids[0])
    for _ in range(rounds):
        rows = assign_clusters(df, centroids, vec).groupBy("cluster_id").agg(*[F.avg(F.col(vec)[j].cast("double")).alias(f"m{j}") for j in range(dim)]).collect()
        centroids = [list(c) for c in centroids]
        for r in rows:
            centroids[r["cluster_id"]] = [round(r[f"m{j}"], 9) for j in range(dim)]
    return centroids


def gate_agreement(verdicts: DataFrame, labels: DataFrame, key: str, pred: str, truth: str) -> DataFrame:
    return verdicts.join(labels.select(key, truth), key).groupBy(pred, truth).agg(F.count("*").alias("n"))


# --- refinement and review -----------------------------------------------------------------------

def refine(df: DataFrame, score: str, keep_fraction: float) -> DataFrame:
    return drop_low_tail(df, score, 1 - keep_fraction)


def review_aggregate(votes: DataFrame, cols: tuple[str, ...], rule: str = "all") -> DataFrame:
    """Adds ``passed``: all criteria, a majority, or a mean of a half and more."""
    total = sum((F.col(c) for c in cols), F.lit(0))
    keep = {"all": total == len(cols), "majority": total * 2 > len(cols), "mean": total * 2 >= len(cols)}[rule]
    return votes.withColumn("passed", keep.cast("int"))


def merge_sources(auto: DataFrame, manual: DataFrame) -> DataFrame:
    return auto.withColumn("provenance", F.lit("auto")).unionByName(manual.withColumn("provenance", F.lit("manual")), allowMissingColumns=True)


def sft_subset(df: DataFrame, cat: str, score: str, key: str, budget: int) -> DataFrame:
    """The best rows of each category, as many from each."""
    cats = df.select(cat).distinct()
    order = W.partitionBy(cat).orderBy(F.desc(score), key)
    ranked = df.withColumn("rn_", F.row_number().over(order))
    per = F.floor(F.lit(budget) / F.col("cats_"))
    return ranked.join(F.broadcast(cats.agg(F.count("*").alias("cats_"))), F.col("rn_") <= per).drop("rn_", "cats_")


# --- annotation ----------------------------------------------------------------------------------

SECTIONS = ("composition", "subject", "motion", "background", "style", "camera", "lighting")  # fixed values: the parts of a description


def lexical_percent(text: Column) -> Column:
    """Distinct words in a hundred."""
    words = F.filter(F.split(text, r"\s+"), lambda w: w != "")
    return F.when(F.size(words) > 0, F.floor(F.size(F.array_distinct(words)) * 100 / F.size(words))).otherwise(0).cast("bigint")


def word_count(text: Column) -> Column:
    return F.size(F.filter(F.split(text, r"\s+"), lambda w: w != "")).cast("bigint")


def route_annotator(df: DataFrame, score: str, cut: Column, light: int = 7, heavy: int = 34) -> DataFrame:
    """The heavy captioner from the cut on, the light one below; cost is units per word."""
    tier = F.when(F.col(score) >= cut, "heavy").otherwise("light")
    return df.withColumn("tier", tier).withColumn("cost", F.col("words") * F.when(F.col("tier") == "heavy", heavy).otherwise(light))


def structured_caption(text: Column) -> Column:
    """A summary (the first line) and seven parts dealt from the other lines in turn."""
    lines = F.split(text, "\n", -1)
    part = lambda k: F.array_join(F.filter(lines, lambda _, i: (i > 0) & ((i - 1) % len(SECTIONS) == k)), " ")
    return F.struct(lines[0].alias("summary"), F.struct(*[part(k).alias(n) for k, n in enumerate(SECTIONS)]).alias("parts"))


def append_scores(caption: Column, scores: dict[str, Column]) -> Column:
    return F.concat(caption, *[F.concat(F.lit(f" | {n}: "), v.cast("string")) for n, v in scores.items()])


def rewrite_prompt(prompt: Column) -> Column:
    """A prompt in the structured template: subject from its first words, the rest as description."""
    words = F.filter(F.split(prompt, r"\s+"), lambda w: w != "")
    return F.concat(F.lit("subject: "), F.array_join(F.slice(words, 1, 4), " "), F.lit("; description: "), F.array_join(F.slice(words, 5, 1000), " "))


def vary_prompt(prompts: DataFrame, attributes: dict[str, list[str]], base: dict[str, str]) -> DataFrame:
    """One row per single-attribute edit: the map of attributes with one value replaced."""
    options = F.array(*[F.struct(F.lit(a).alias("attribute"), F.lit(v).alias("value")) for a, vs in attributes.items() for v in vs])
    start = F.create_map(*[F.lit(x) for kv in base.items() for x in kv])
    edited = F.transform_values(start, lambda k, v: F.when(k == F.col("o.attribute"), F.col("o.value")).otherwise(v))
    return prompts.withColumn("o", F.explode(options)).withColumn("edited", edited).select(*prompts.columns, "o.attribute", "o.value", "edited")


def cosine_to(vec: Column, other: Column) -> Column:
    return dot(vec, other) / (norm(vec) * norm(other))
