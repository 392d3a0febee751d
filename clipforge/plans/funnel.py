"""Curation funnels: operators declared in a configuration, ordered by measured cost and selectivity.

Catalyst keeps the order of filters that it cannot cost, so the order is chosen
here, before the plan is made. Statistics come from one aggregate: every row's
verdicts form a bit mask, and the counts of at most 2**m masks are all that any
ordering question needs.
"""

from __future__ import annotations

import itertools
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from clipforge.functions.exprs import key_int


@dataclass(frozen=True)
class Placement:
    """Where an operator runs. Expression operators always run on cores."""

    kind: str = "cpu"
    cores: int = 1
    accel: int = 0
    batch_rows: int = 10_000

    def profile(self):
        """A resource profile for mapInPandas, or None where the default will do."""
        if self.kind == "cpu" and self.cores == 1:
            return None
        from pyspark.resource import ExecutorResourceRequests, ResourceProfileBuilder, TaskResourceRequests

        task, executor = TaskResourceRequests().cpus(self.cores), ExecutorResourceRequests().cores(self.cores)
        if self.accel:
            task, executor = task.resource("gpu", self.accel), executor.resource("gpu", self.accel)
        return ResourceProfileBuilder().require(task).require(executor).build

    def map(self, df: DataFrame, batches: Callable, schema: str) -> DataFrame:
        """``mapInPandas`` where this placement says: in batches of ``batch_rows``, under its resource profile (one machine has no other to offer)."""
        size = self.batch_rows

        def cut(stream):
            for pdf in stream:
                yield from batches(pdf.iloc[a:a + size] for a in range(0, len(pdf), size))

        local = df.sparkSession.sparkContext.master.split("[")[0] == "local"
        return df.mapInPandas(cut, schema, profile=None if local else self.profile())


@dataclass(frozen=True)
class Op:
    """A step of a funnel: a filter by ``keep``, any transformation by ``run``, or a function of Pandas ``batches`` to rows of ``schema`` that runs where ``place`` says."""

    name: str
    keep: Column | None = None
    run: Callable[[DataFrame], DataFrame] | None = None
    batches: Callable | None = None
    schema: str = ""
    cost: int = 1
    place: Placement = field(default_factory=Placement)
    after: tuple[str, ...] = ()
    applies_to: tuple[str, ...] = ("image", "video")

    def verdict(self) -> Column:
        """The filter's verdict; media of a kind that the operator is not for pass."""
        if self.applies_to == ("video",):
            return F.when(F.col("frames") == 1, F.lit(True)).otherwise(F.coalesce(self.keep, F.lit(False)))
        return F.coalesce(self.keep, F.lit(False))


@dataclass(frozen=True)
class Pipeline:
    ops: tuple[Op, ...]

    def run(self, df: DataFrame) -> DataFrame:
        for op in self.ops:
            if op.keep is not None:
                df = df.filter(op.verdict())
            else:
                df = op.run(df) if op.run else op.place.map(df, op.batches, op.schema)
        return df

    def in_order(self) -> Pipeline:
        """The steps so that each stands behind those that it comes after, otherwise as declared."""
        left, out = list(self.ops), []
        while left:
            names = {op.name for op in left}
            ready = next((op for op in left if not set(op.after) & (names - {op.name})), None)
            if ready is None:
                raise ValueError(f"steps wait for each other: {sorted(names)}")
            left.remove(ready)
            out.append(ready)
        return Pipeline(tuple(out))


REGISTRY: dict[str, Callable[..., Op]] = {}


def register(name: str):
    """Makes an operator known to configurations."""
    def wrap(make):
        REGISTRY[name] = make
        return make

    return wrap


def build_pipeline(conf: dict) -> Pipeline:
    """A pipeline from ``{"ops": [{"op": name, ...parameters}]}``."""
    return Pipeline(tuple(REGISTRY[c["op"]](**{k: v for k, v in c.items() if k != "op"}) for c in conf["ops"]))


def profile_ops(df: DataFrame, ops: list[Op], permille: int = 1000, key: str = "media_id") -> dict[int, int]:
    """Rows by bit mask of verdicts (bit i: operator i passes), over a keyed sample."""
    if permille < 1000:
        df = df.filter(key_int(F.col(key)) % 1000 < permille)
    mask = sum((F.shiftleft(op.verdict().cast("int"), i) for i, op in enumerate(ops)), F.lit(0))
    return {r["mask"]: r["n"] for r in df.groupBy(mask.alias("mask")).agg(F.count("*").alias("n")).collect()}


def passes(masks: dict[int, int], bits: int) -> int:
    """Rows that pass every operator of ``bits``."""
    return sum(n for m, n in masks.items() if m & bits == bits)


def expected_work(order: list[int], masks: dict[int, int], costs: list[int]) -> int:
    """Sum over operators of cost times the rows that reach it."""
    work, bits = 0, 0
    for i in order:
        work += costs[i] * passes(masks, bits)
        bits |= 1 << i
    return work


def order_ops(ops: list[Op], masks: dict[int, int], policy: str = "rank") -> list[int]:
    """Places of the operators in the order of a policy, precedence honoured.

    tightest: lowest pass rate first; resource: cores before accelerators, then
    cheaper; throughput: cheapest first; rank: cores first, then cost over the
    rate of rejection; declared, reverse; exhaustive: the cheapest permutation
    for the measured verdicts (at most seven operators).
    """
    n, total = len(ops), max(1, sum(masks.values()))
    passed = [passes(masks, 1 << i) for i in range(n)]
    tier = [int(op.place.kind != "cpu") for op in ops]
    if policy == "exhaustive":
        if n > 7:
            raise ValueError("exhaustive ordering takes at most seven operators")
        legal = [p for p in itertools.permutations(range(n)) if _legal(p, ops)]
        return list(min(legal, key=lambda p: (expected_work(list(p), masks, [o.cost for o in ops]), p)))
    key = {
        "tightest": lambda i: (passed[i], i),
        "resource": lambda i: (tier[i], ops[i].cost, i),
        "throughput": lambda i: (ops[i].cost, i),
        "rank": lambda i: (tier[i], ops[i].cost * total / (total - passed[i]) if passed[i] < total else float("inf"), i),
        "declared": lambda i: i,
        "reverse": lambda i: -i,
    }[policy]
    left, out = sorted(range(n), key=key), []
    while left:  # the first that waits for nothing
        i = next(i for i in left if not set(ops[i].after) & {ops[j].name for j in left})
        left.remove(i)
        out.append(i)
    return out


def _legal(order: tuple, ops: list[Op]) -> bool:
    place = {ops[i].name: k for k, i in enumerate(order)}
    return all(place.get(a, -1) < place[ops[i].name] for i in order for a in ops[i].after)


def funnel_ledger(df: DataFrame, ops: list[Op]) -> DataFrame:
    """Step, operator, rows in and out, pass rate and cost, from one scan."""
    through, counts = F.lit(True), [F.count("*").alias("n0")]
    for i, op in enumerate(ops):
        through = through & op.verdict()
        counts.append(F.count_if(through).alias(f"n{i + 1}"))
    one = df.agg(*counts)
    steps = F.array(*[F.struct(F.lit(i + 1).cast("bigint").alias("step"), F.lit(op.name).alias("op"), F.col(f"n{i}").alias("rows_in"), F.col(f"n{i + 1}").alias("rows_out"),
                               (F.col(f"n{i}") * op.cost).cast("bigint").alias("cost")) for i, op in enumerate(ops)])
    out = one.select(F.explode(steps).alias("s")).select("s.*")
    return out.withColumn("pass_rate", F.round(F.when(F.col("rows_in") > 0, F.col("rows_out") / F.col("rows_in")).otherwise(0.0), 6))
