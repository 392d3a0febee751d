"""Metadata filters, funnels and their orders."""

from __future__ import annotations

from pyspark.sql import functions as F

from clipforge.operators import container
from clipforge.plans.funnel import Op, Pipeline, Placement, build_pipeline, expected_work, funnel_ledger, order_ops, passes, profile_ops, register
from clipforge.sources import tables as T

from .sqlviews import h, using

ASPECT, FPS, RATE, DURATION, STATUS = "width * 10 >= height * 4 and width * 10 <= height * 25", "fps >= 16", "sample_rate >= 22050", "frames >= fps * 2", "status <> 'P'"
SQL_CHECKS = {"aspect": ASPECT, "fps": FPS, "rate": RATE, "duration": DURATION, "status": STATUS}
COSTS = {"aspect": 3, "fps": 1, "rate": 2, "duration": 5, "status": 40}


def gate_ops() -> list[Op]:
    """The five checks with unit costs; the decode probe stands for one on an accelerator."""
    checks = container.gate_checks()
    return [Op(n, keep=checks[n], cost=COSTS[n], place=Placement("accel" if n == "status" else "cpu"), applies_to=("video",) if n in ("fps", "duration") else ("image", "video")) for n in checks]


def plain_ops() -> list[Op]:
    checks = container.gate_checks()
    return [Op(n, keep=checks[n], cost=COSTS[n], place=Placement("accel" if n == "status" else "cpu")) for n in checks]


@register("metadata")
def metadata_op(check: str, cost: int = 1) -> Op:
    return Op(check, keep=container.gate_checks()[check], cost=cost)


@register("text")
def text_op(check: str, **limits) -> Op:
    """Text gates: least length, share of signs."""
    keep = {"length": lambda: F.col("len") >= limits.get("least", 20), "signs": lambda: F.regexp_count("line", F.lit(r"[*$%&#!|]")) * 10 <= F.col("len")}[check]()
    return Op(check, keep=keep, cost=1)


def _where(name):
    return lambda spark, d: T.media_meta(spark, d).filter(container.gate_checks()[name]).select("media_id")


def _order(policy):
    def query(spark, d):
        ops, df = plain_ops(), T.media_meta(spark, d)
        masks = profile_ops(df, ops)
        order = order_ops(ops, masks, policy)
        work = expected_work(order, masks, [o.cost for o in ops])
        ledger = funnel_ledger(df, [ops[i] for i in order])
        return ledger.select("step", "op", "rows_out", F.lit(work).cast("bigint").alias("total_work"))
    return query


def _order_sql(rank: str) -> str:
    """The order from its definition: pass counts per check, sorted by ``rank``, then survivors of each prefix."""
    flags = ", ".join(f"({c}) as {n}" for n, c in SQL_CHECKS.items())
    stats = " union all ".join(f"select '{n}' as op, {i} as pos, {COSTS[n]} as cost, {int(n == 'status')} as tier, count(*) filter ({n}) as passed, count(*) as total from f" for i, n in enumerate(SQL_CHECKS))
    fails = " and ".join(f"(not list_contains(o.ops, '{n}') or f.{n})" for n in SQL_CHECKS)
    return using("media_meta", sql=f"""f as (select {flags} from media_meta), stats as ({stats}),
      ranked as (select *, row_number() over (order by {rank}) as step from stats),
      o as (select step, op, cost, list(op) over (order by step) as ops, total from ranked),
      r as (select o.step, o.op, o.cost, (select count(*) from f where {fails}) as rows_out, o.total from o),
      w as (select *, cost * coalesce(lag(rows_out) over (order by step), total) as work from r)
      select step, op, rows_out, cast((select sum(work) from w) as bigint) as total_work from w""")


def funnel_order_cost(spark, d):
    """Total work of every policy, and of the best permutation."""
    ops = plain_ops()
    masks = profile_ops(T.media_meta(spark, d), ops)
    rows = [(p, int(expected_work(order_ops(ops, masks, p), masks, [o.cost for o in ops]))) for p in ("declared", "reverse", "tightest", "resource", "throughput", "rank", "exhaustive")]
    return spark.createDataFrame(rows, "policy string, total_work bigint")


def _cost_sql() -> str:
    flags = ", ".join(f"({c}) as {n}" for n, c in SQL_CHECKS.items())
    names = list(SQL_CHECKS)
    stats = " union all ".join(f"select '{n}' as op, {i} as pos, {COSTS[n]} as cost, {int(n == 'status')} as tier, count(*) filter ({n}) as passed, count(*) as total from f" for i, n in enumerate(names))
    # every permutation by joining the five operators with themselves
    frm = ", ".join(f"stats s{i}" for i in range(5))
    diff = " and ".join(f"s{i}.op <> s{j}.op" for i in range(5) for j in range(i))
    sel = ", ".join(f"s{i}.op" for i in range(5))
    subsets = "select b, (select count(*) from f where " + " and ".join(f"((b & {1 << i}) = 0 or {n})" for i, n in enumerate(names)) + ") as n from range(32) t(b)"
    work = " + ".join(f"s{i}.cost * (select n from subsets where b = {' + '.join([f'(1 << s{j}.pos)' for j in range(i)]) or '0'})" for i in range(5))
    ranks = {"declared": "pos", "reverse": "-pos", "tightest": "passed, pos", "resource": "tier, cost, pos", "throughput": "cost, pos", "rank": "tier, case when passed < total then cost * total / (total - passed) else 1e300 end, pos"}
    picked = " union all ".join(f"select '{p}' as policy, (select list(op order by {r}) from stats) as ops" for p, r in ranks.items())
    return using("media_meta", sql=f"""f as (select {flags} from media_meta), stats as ({stats}), subsets as materialized ({subsets}),
      perms as (select [{sel}] as ops, {work} as work from {frm} where {diff})
      select p.policy, cast(q.work as bigint) as total_work from ({picked}) p join perms q on p.ops = q.ops
      union all select 'exhaustive', cast(min(work) as bigint) from perms""")


def op_profile_sample(spark, d):
    """Passes of each check and of all, over a keyed tenth."""
    ops = plain_ops()
    masks = profile_ops(T.media_meta(spark, d), ops, permille=100)
    rows = [(o.name, passes(masks, 1 << i), sum(masks.values())) for i, o in enumerate(ops)] + [("all", passes(masks, 31), sum(masks.values()))]
    return spark.createDataFrame([(n, int(p), int(t)) for n, p, t in rows], "op string, passed bigint, sampled bigint")


def funnel_text(spark, d):
    """Lines that are long, plain, safe and not seen before, counted by language."""
    conf = {"ops": [{"op": "text", "check": "length", "least": 20}, {"op": "text", "check": "signs"}]}
    toxic = T.load(spark, d, "labels").filter("toxic = 1").select("doc_id")
    safe = Op("safe", run=lambda df: df.join(toxic, "doc_id", "left_anti"))
    once = Op("once", run=lambda df: df.groupBy(F.md5("line").alias("k")).agg(F.min(F.struct("doc_id", "clip_no", "lang")).alias("m")).select("m.*"))
    out = Pipeline((*build_pipeline(conf).ops, safe, once)).run(T.text_clips(spark, d))
    return out.groupBy("lang").agg(F.count("*").alias("n"), F.sum("doc_id").cast("bigint").alias("docs_sum"))


def media_fps_query(spark, d):
    return _where("fps")(spark, d)


def frame_sample_flags(spark, d):
    return container.sampled_frame_check(T.frames(spark, d), F.col("kind") == "error")


QUERIES = {
    "media_aspect_filter": _where("aspect"), "media_fps_filter": _where("fps"), "media_rate_filter": _where("rate"), "media_duration_filter": _where("duration"),
    "media_reject_reasons": lambda s, d: container.metadata_gate(T.media_meta(s, d)).select(F.explode("reasons").alias("reason")).groupBy("reason").agg(F.count("*").alias("n")),
    "frame_sample_flags": frame_sample_flags,
    "page_diagnostics": lambda s, d: T.load(s, d, "pages").select("page_id", container.diagnose(F.col("html")).alias("code")),
    "media_filter_rollup": lambda s, d: container.video_level_report(container.metadata_gate(T.media_meta(s, d))),
    "funnel_ledger": lambda s, d: funnel_ledger(T.media_meta(s, d), plain_ops()),
    "funnel_image_subset": lambda s, d: funnel_ledger(T.media_meta(s, d).filter("frames = 1"), gate_ops()),
    "funnel_order_tightest": _order("tightest"), "funnel_order_resource": _order("resource"), "funnel_order_throughput": _order("throughput"), "funnel_order_rank": _order("rank"),
    "funnel_order_cost": funnel_order_cost, "op_profile_sample": op_profile_sample, "funnel_text": funnel_text,
}


def _ledger_sql(checks: dict[str, str], where: str) -> str:
    parts, through = [], "true"
    for i, (n, c) in enumerate(checks.items()):
        parts.append(f"select cast({i + 1} as bigint) as step, '{n}' as op, count(*) filter ({through}) as rows_in, count(*) filter ({through} and ({c})) as rows_out, cast(count(*) filter ({through}) * {COSTS[n]} as bigint) as cost from m")
        through += f" and ({c})"
    return using("media_meta", sql=f"m as (select * from media_meta where {where}), l as ({' union all '.join(parts)}) select *, round(case when rows_in > 0 then rows_out / rows_in else 0.0 end, 6) as pass_rate from l")


ORACLES = {
    **{f"media_{n}_filter": using("media_meta", sql=f"select media_id from media_meta where {c}") for n, c in SQL_CHECKS.items() if n != "status"},
    "media_reject_reasons": using("media_meta", sql=" union all ".join(f"select '{n}' as reason, count(*) as n from media_meta where not ({c}) having count(*) > 0" for n, c in SQL_CHECKS.items())),
    "frame_sample_flags": using("frames", sql=f"""p as (select *, row_number() over (partition by media_id order by {h("cast(media_id as varchar) || '_' || cast(frame_no as varchar)")}, frame_no) as pick from frames)
        select media_id, count(*) as sampled, count(*) filter (kind = 'error') as flagged, cast(count(*) filter (kind = 'error') <= count(*) * 0.25 as integer) as keep from p where pick <= 8 group by 1"""),
    "page_diagnostics": """select page_id, case when html is null or html = '' then 'empty' when contains(html, '�') then 'encoding' when not ends_with(html, '</html>') then 'truncated'
        when len(string_split(html, '<script')) <> len(string_split(html, '</script>')) then 'unbalanced' else 'ok' end as code from pages""",
    "media_filter_rollup": using("media_meta", sql=f"select status, sample_rate, count(*) as n, count(*) filter ({' and '.join(f'({c})' for c in SQL_CHECKS.values())}) as passed from media_meta group by rollup (status, sample_rate)"),
    "funnel_ledger": _ledger_sql(SQL_CHECKS, "true"),
    "funnel_image_subset": _ledger_sql({**SQL_CHECKS, "fps": "true", "duration": "true"}, "frames = 1"),
    "funnel_order_tightest": _order_sql("passed, pos"), "funnel_order_resource": _order_sql("tier, cost, pos"), "funnel_order_throughput": _order_sql("cost, pos"),
    "funnel_order_rank": _order_sql("tier, case when passed < total then cost * total / (total - passed) else 1e300 end, pos"),
    "funnel_order_cost": _cost_sql(),
    "op_profile_sample": using("media_meta", sql=f"s as (select * from media_meta where {h('cast(media_id as varchar)')} % 1000 < 100) " + " union all ".join(
        f"select '{n}' as op, count(*) filter ({c}) as passed, count(*) as sampled from s" for n, c in {**SQL_CHECKS, "all": " and ".join(f"({c})" for c in SQL_CHECKS.values())}.items())),
    "funnel_text": using("text_clips", sql=r"""g as (select * from text_clips where len >= 20 and (len - length(regexp_replace(line, '[*$%&#!|]', '', 'g'))) * 10 <= len
        and doc_id not in (select doc_id from labels where toxic = 1)), r as (select *, row_number() over (partition by line order by doc_id, clip_no) as k from g)
        select lang, count(*) as n, cast(sum(doc_id) as bigint) as docs_sum from r where k = 1 group by 1"""),
}
