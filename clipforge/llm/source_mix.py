"""Mixing sources to target weights by min-cost flow.

Documents are aggregated by membership pattern (the set of sources a document
belongs to). Each pattern offers its tokens up to ``max_repeats`` times, the
first time free and each further time dearer, so costs are convex. A flow from
patterns to source quotas says how many tokens each (pattern, source) pair
gives, and seeded documents fill that number.

All patterns go through the flow, those of one source too. Patterns that share
no source with each other, directly or in steps, cannot give each other way, so
each such group is a flow of its own. What comes to the driver is one row of sums
for each pattern, never a document; the plan goes back to the executors by a
broadcast up to ``MAX_BROADCAST`` patterns or sources, and by a shuffle beyond.

Null texts and texts of white space have size 0 and are taken 0 times. Null
sources form a source of their own, last in order. Rows that repeat are each
offered. An empty table gives no rows. Other columns pass through
``mix_documents`` untouched.
"""

from __future__ import annotations

import heapq
from collections import defaultdict

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialize, table

MAX_BROADCAST = 10_000
WORD = r"[^\x20\x09-\x0D]+"
SEED = 20


def text_size(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def fill_targets(sizes: dict, weights: dict, cap: float = 3.0) -> dict:
    """Shares of the whole by weight; what lies above ``cap`` times a source's size is shared again among the rest."""
    total, fixed = float(sum(sizes.values())), {}
    while True:
        free = [s for s in sizes if s not in fixed]
        left, weight = total - sum(fixed.values()), sum(weights[s] for s in free)
        share = {s: left * weights[s] / weight for s in free}
        over = [s for s in free if share[s] > cap * sizes[s]]
        if not over:
            return {**fixed, **share}
        fixed |= {s: cap * sizes[s] for s in over}


def cycle_weights(sources: list, cycle=(1, 2, 3)) -> dict:
    """Sources by code point, null last, weigh the cycle's numbers in turn."""
    order = sorted((s for s in sources if s is not None), key=lambda s: s.encode("utf-8")) + [None] * (None in sources)
    return {s: cycle[i % len(cycle)] for i, s in enumerate(order)}


def route(supply: dict[tuple, int], quota: dict, max_repeats: int = 3) -> dict[tuple, float]:
    """Min-cost flow from patterns to quotas by successive shortest paths.

    An arc into a pattern stands for one repeat of its tokens and costs that
    repeat's number, so cheap first passes fill before any text is repeated.
    Gives (pattern, source) -> tokens.
    """
    graph: dict = defaultdict(dict)
    cost: dict = {}

    def arc(a, b, room, price):
        graph[a][b], graph[b][a] = graph[a].get(b, 0) + room, graph[b].get(a, 0)
        cost[a, b], cost[b, a] = price, -price

    for p, size in supply.items():
        for k in range(max_repeats):
            arc("from", ("pass", p, k), size, k)
            arc(("pass", p, k), ("pattern", p), size, 0)
        for s in p:
            if s in quota:
                arc(("pattern", p), ("source", s), size * max_repeats, 0)
    for s, q in quota.items():
        arc(("source", s), "to", q, 0)
    height: dict = defaultdict(int)
    while True:
        best, came, heap = {"from": 0}, {}, [(0, 0, "from")]
        tick = 0
        while heap:
            d, _, a = heapq.heappop(heap)
            if d > best[a]:
                continue
            for b, room in graph[a].items():
                step = d + cost[a, b] + height[a] - height[b]
                if room > 1e-9 and step < best.get(b, 1 << 60):
                    best[b], came[b] = step, a
                    tick += 1
                    heapq.heappush(heap, (step, tick, b))
        if "to" not in best:
            break
        for a, d in best.items():
            height[a] += d
        path, b = [], "to"
        while b != "from":
            path.append((came[b], b))
            b = came[b]
        flow = min(graph[a][b] for a, b in path)
        for a, b in path:
            graph[a][b] -= flow
            graph[b][a] += flow
    return {(p, s): graph["source", s].get(("pattern", p), 0) for p in supply for s in p if s in quota}


def route_groups(supply: dict[tuple, int], quota: dict, max_repeats: int = 3) -> dict[tuple, float]:
    """Tokens that each pattern gives, by one flow for each group of patterns that share sources."""
    root: dict = {}

    def find(s):
        while root.setdefault(s, s) != s:
            root[s] = root[root[s]]
            s = root[s]
        return s

    for p in supply:
        for s in p[1:]:
            root[find(s)] = find(p[0])
    groups: dict = defaultdict(dict)
    for p, n in sorted(supply.items(), key=lambda x: [(s is None, s or "") for s in x[0]]):  # so that of equally good flows the same is found again
        if p:
            groups[find(p[0])][p] = n
    given = dict.fromkeys(supply, 0.0)
    for group in groups.values():
        for (p, _), f in route(group, {s: quota[s] for p in group for s in p}, max_repeats).items():
            given[p] += f
    return given


def _fill(pdf: pd.DataFrame) -> pd.DataFrame:
    """One boundary bin: in seeded order, every document that still fits."""
    pdf = pdf.sort_values(["draw", "row"], kind="stable")
    room, takes = pdf["room"].iloc[0], []
    for size in pdf["size"].tolist():
        fits = 0 < size <= room
        takes.append(int(fits))
        room -= size if fits else 0
    return pdf.assign(extra=takes)[["row", "extra"]]


def _small(df: DataFrame, n: int) -> DataFrame:
    return F.broadcast(df) if n <= MAX_BROADCAST else df


def plan_mix(docs: DataFrame, key: Column, sources: Column, cycle=(1, 2, 3), max_repeats: int = 3, seed: int = SEED, bin_rows: int = 5000) -> tuple[DataFrame, DataFrame, int]:
    """(rows with ``key``, ``pattern``, ``size`` and ``copies``; sources with their size and target; how many sources).

    ``sources`` is an array of source names, ``key`` what names a row. A
    document's copies are the whole passes its pattern gives plus at most one
    more, drawn by a seeded hash: all bins of the hash below the boundary, and in
    the boundary bin, which holds about ``bin_rows`` rows, each that still fits.
    """
    spark = docs.sparkSession
    draw = F.pmod(F.xxhash64(F.lit(seed), key, F.col("text")), F.lit(1 << 30))
    rows = docs.select(key.alias("key"), F.array_sort(F.array_distinct(sources)).alias("pattern"), text_size(F.col("text")).alias("size"), draw.alias("draw"))
    rows = materialize(rows.withColumn("row", F.monotonically_increasing_id()), "mix-rows")
    patterns = rows.groupBy("pattern").agg(F.sum("size").alias("supply"), F.count("*").alias("n")).collect()
    supply = {tuple(r["pattern"]): int(r["supply"]) for r in patterns}
    count = {tuple(r["pattern"]): int(r["n"]) for r in patterns}
    sizes: dict = defaultdict(int)
    for p, size in supply.items():
        for s in p:
            sizes[s] += size
    sizes = dict(sorted(sizes.items(), key=lambda x: (x[0] is None, x[0] or "")))
    targets = fill_targets(sizes, cycle_weights(list(sizes), cycle), float(max_repeats)) if sum(sizes.values()) else dict.fromkeys(sizes, 0.0)
    flow = route_groups(supply, targets, max_repeats)
    plans = []
    for p, size in supply.items():
        base = min(max_repeats, int((flow[p] + 1e-6) // size)) if size else 0
        plans.append((list(p), base, int(round(flow[p] - base * size)) if base < max_repeats else 0, max(1, -(-count[p] // bin_rows))))
    plan = spark.createDataFrame(plans, "p array<string>, base int, wanted long, bins int")
    tagged = rows.join(_small(plan, len(plans)), F.col("pattern").eqNullSafe(F.col("p"))).drop("p")
    tagged = tagged.withColumn("bin", F.floor(F.col("draw") * F.col("bins") / F.lit(float(1 << 30))).cast("int"))
    by_bin = tagged.groupBy("pattern", "bin").agg(F.sum("size").alias("bin_size"), F.first("wanted").alias("wanted"))
    up = F.sum("bin_size").over(W.partitionBy("pattern").orderBy("bin").rowsBetween(W.unboundedPreceding, 0))
    by_bin = by_bin.withColumn("upto", up).withColumn("room", F.col("wanted") - F.col("upto") + F.col("bin_size"))
    by_bin = by_bin.select(F.col("pattern").alias("p"), F.col("bin").alias("b"), F.col("room"), (F.col("upto") <= F.col("wanted")).alias("whole"))
    ranked = materialize(tagged.join(by_bin, F.col("pattern").eqNullSafe(F.col("p")) & (F.col("bin") == F.col("b"))).drop("p", "b"), "mix-bins")
    edge = ranked.filter("not whole and room > 0").groupBy("pattern", "bin").applyInPandas(_fill, "row long, extra int")
    copies = F.when(F.col("size") == 0, 0).otherwise(F.col("base") + F.when(F.col("whole"), 1).otherwise(F.coalesce("extra", F.lit(0))))
    ranked = ranked.join(edge, "row", "left").select("key", "pattern", "size", copies.alias("copies"))
    return ranked, spark.createDataFrame([(s, int(sizes[s]), float(targets[s])) for s in sizes], "name string, source_size long, target double"), len(sizes)


def mix_sources(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, size, source_size, target, taken."""
    ranked, sources, n = plan_mix(docs, F.col("doc_id").cast("long"), F.array(F.col("source").cast("string")))
    out = ranked.join(_small(sources, n), F.col("pattern")[0].eqNullSafe(F.col("name")))
    return out.select(F.col("key").alias("doc_id"), "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def _row_key(docs: DataFrame, seed: int) -> Column:
    """A hash of all that a row holds, nulls and maps too."""
    parts = []
    for f in docs.schema:
        c = F.col(f"`{f.name}`")
        parts += [c.isNull(), F.to_json(F.struct(c), {"ignoreNullFields": "false"}) if "map<" in f.dataType.simpleString() else c]
    return F.xxhash64(F.lit(seed), *parts)


def mix_documents(docs: DataFrame, part: int = 10_000) -> DataFrame:
    """The mixed corpus: every row as often as the mix takes it, with all its columns.

    Rows are named by two hashes of all that they hold, so the name is the same in
    both reads. Equal rows share their takes: one of them stands for all, repeated
    in parts of ``part`` rows, so no task makes more than that of one row at once.
    """
    tagged = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row_"), _row_key(docs, 1).alias("k1_"), _row_key(docs, 2).alias("k2_"))
    key = F.struct("k1_", "k2_")
    ranked, _, _ = plan_mix(tagged.select("k1_", "k2_", F.col("row_.text").alias("text"), F.col("row_.source").cast("string").alias("source")), key, F.array("source"))
    takes = ranked.groupBy("key.k1_", "key.k2_").agg(F.sum("copies").alias("takes_"), F.count("*").alias("n_")).filter("takes_ > 0")
    out = tagged.join(takes, ["k1_", "k2_"])
    single = out.filter("n_ = 1").withColumn("nth_", F.explode(F.sequence(F.lit(1), F.col("takes_").cast("int"))))
    several = out.filter("n_ > 1").dropDuplicates(["k1_", "k2_"]).withColumn("part_", F.explode(F.sequence(F.lit(0), F.floor((F.col("takes_") - 1) / part))))
    several = several.repartition("k1_", "k2_", "part_").withColumn("nth_", F.explode(F.sequence(F.lit(1), F.least(F.lit(part), F.col("takes_") - part * F.col("part_")).cast("int"))))
    return single.select("row_").unionByName(several.select("row_")).select(*[F.col("row_")[c].alias(c) for c in docs.columns])


def op6_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(table(spark, sf_dir, "documents"))
