"""Attention, rotary encoding, conditioning and experts."""

from __future__ import annotations

from pyspark.sql import functions as F

from clipforge.functions.exprs import norm, rnd
from clipforge.operators import attention as A
from clipforge.sources import tables as T

from .sqlviews import using


def toks(s, d):
    return T.latents(s, d).select("item", F.col("i").alias("tok"), "val")


def group_of(kind):
    return {"full": None, "stride": [A.stride_group(F.col("tok"))], "block": [A.block_group(F.col("tok"))]}[kind]


def att(kind):
    return lambda s, d: A.attend(toks(s, d), group_of(kind)).select("item", "tok", rnd(F.col("out")).alias("out"), "pairs")


def separated(s, d):
    return A.attend_separated(T.latents(s, d)).select("item", "tok", rnd(F.col("out")).alias("out"), "pairs")


def cost(s, d):
    """Per arm: score pairs, mean squared distance to full attention."""
    full = A.attend(toks(s, d)).select("item", "tok", F.col("out").alias("full"))
    out = None
    for name, df in (("full", A.attend(toks(s, d))), ("stride", A.attend(toks(s, d), group_of("stride"))), ("block", A.attend(toks(s, d), group_of("block"))), ("separated", A.attend_separated(T.latents(s, d)))):
        row = df.join(full, ["item", "tok"]).agg(F.lit(name).alias("arm"), F.sum("pairs").cast("bigint").alias("pairs"), rnd(F.avg((F.col("out") - F.col("full")) * (F.col("out") - F.col("full"))) + 1e-12, 8).alias("distance"))
        out = row if out is None else out.unionByName(row)
    return out


def reachability(s, d):
    t = toks(s, d).filter("item = 0")
    stride, block = A.stride_group(F.col("tok")), A.block_group(F.col("tok"))
    out = None
    for name, gs in (("stride_stride", [stride, stride]), ("stride_block", [stride, block]), ("full", [F.lit(0)])):
        row = A.reach(t, gs).agg(F.lit(name).alias("arm"), F.count("*").alias("reached"))
        out = row if out is None else out.unionByName(row)
    return out


def texts(s, d):
    """Label centroids stand for text tokens."""
    e = T.load(s, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "v"))
    c = e.groupBy("label", "i").agg(F.avg(F.col("v").cast("double")).alias("m")).groupBy("label").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "m"))), lambda x: x["m"]).alias("key"))
    return c.select(F.col("label").alias("tid"), "key", F.col("label").cast("double").alias("value"))


def joint(s, d):
    text = T.load(s, d, "benchmark").select(F.col("item_id").alias("item"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(3).cast("bigint"))).alias("tok"), (F.length("text") % 10 / 10).alias("val"))
    return A.joint_attend(toks(s, d), text).select("item", "tok", rnd(F.col("out")).alias("out"), "pairs")


def rope(s, d):
    e = T.load(s, d, "embeddings")
    v = A.rope3d(F.col("embedding"), F.col("vec_id") % 8, F.col("vec_id") % 5, F.col("vec_id") % 3, (16, 24, 24))
    return e.select("vec_id", v.alias("r"), "embedding").select("vec_id", rnd(F.aggregate(F.transform("r", lambda x, i: x * (i + 1)), F.lit(0.0), lambda a, x: a + x) + 1e-10, 5).alias("placed"), rnd(norm(F.col("r")) - norm(F.col("embedding"))).alias("norm_change"))


def rope_bases(s, d):
    """Mean squared change of the vector when time moves by one, for two bases."""
    e = T.load(s, d, "embeddings")
    out = None
    for base in (10_000.0, 256.0):
        a, b = (A.rope1d(F.col("embedding"), F.lit(p), 64, base) for p in (1, 2))
        row = e.agg(F.lit(int(base)).cast("bigint").alias("base"), rnd(F.avg(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s_, x: s_ + x))).alias("change"))
        out = row if out is None else out.unionByName(row)
    return out


def routed(s, d):
    return A.route_topk(T.load(s, d, "embeddings"), "vec_id", F.col("embedding"))


def moe_ratio(s, d):
    rows = [("experts_total", 66.0), ("experts_active", 8.0), ("active_width", 8 * 0.25), ("param_share", 1.7 / 10), ("dense_width", 1.0), ("per_device", 64 / 8)]
    return s.createDataFrame([(n, float(round(v, 6))) for n, v in rows], "measure string, value double")


def conditioned(s, d):
    e = T.load(s, d, "embeddings")
    v = A.condition(A.time_features(F.col("vec_id") % 10 / 10, 64), F.col("embedding"))
    return e.select("vec_id", rnd(F.aggregate(F.transform(v, lambda x, i: x * (i + 1)), F.lit(0.0), lambda a, x: a + x) + 1e-10, 5).alias("placed"))


def identity(s, d):
    e = T.load(s, d, "embeddings")
    v = F.transform("embedding", lambda x: x.cast("double"))
    sq = lambda a: F.aggregate(F.zip_with(a, v, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s_, x: s_ + x)
    return e.agg(rnd(F.sum(sq(A.modulate(v, F.lit(0.5), F.lit(0.2), F.lit(0.0))))).alias("gate_zero"), rnd(F.avg(sq(A.modulate(v, F.lit(0.5), F.lit(0.2), F.lit(1.0)))) + 1e-10, 5).alias("gate_one"))


QUERIES = {
    "attention_full": att("full"), "attention_sparse_stride": att("stride"), "attention_sparse_block": att("block"), "attention_separated": separated,
    "attention_cost": cost, "attention_reach": reachability,
    "cross_attention": lambda s, d: A.cross_attend(T.load(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec")), texts(s, d)).select("id", rnd(F.col("out") + 1e-10, 5).alias("out")),
    "joint_attention": joint, "rope3d_rotate": rope, "rope_base_sensitivity": rope_bases,
    "modulation_params": lambda s, d: s.createDataFrame([(40, 3072, True), (40, 3072, False)], "blocks bigint, hidden bigint, shared boolean").select(F.col("shared").cast("int").alias("shared"), A.modulation_params(F.col("blocks"), F.col("hidden"), F.col("shared")).alias("params")),
    "modulate_identity": identity, "time_condition": conditioned,
    "moe_topk_routing": lambda s, d: routed(s, d).select("vec_id", "expert", rnd(F.col("weight")).alias("weight")),
    "moe_load": lambda s, d: A.expert_load(routed(s, d)).select("expert", "load", rnd(F.col("over_mean")).alias("over_mean"), "overflow"),
    "moe_device_traffic": lambda s, d: routed(s, d).filter("expert >= 0").groupBy((F.col("vec_id") % 8).alias("source_device"), A.expert_device(F.col("expert")).alias("device")).agg(F.count("*").alias("tokens")),
    "moe_param_ratio": moe_ratio,
    "pipeline_partition": lambda s, d: A.pipeline_partition(A.layer_table(s, 40), 4).groupBy("stage").agg(F.count("*").alias("layers"), F.sum("cost").cast("bigint").alias("cost")),
}

_TOK = "tk as (select item, i as tok, val from latents)"


def _att(g):
    return f"select q.item, q.tok, round(sum(exp(q.val * k.val) * k.val) / sum(exp(q.val * k.val)), 6) + 0.0 as out, count(*) as pairs from tk q join tk k on q.item = k.item and {g} group by 1, 2"


_RAW = "select q.item, q.tok, sum(exp(q.val * k.val) * k.val) / sum(exp(q.val * k.val)) as out, count(*) as pairs from {t} q join {t} k on q.item = k.item and {g} group by 1, 2"
_STRIDE, _BLOCK = "q.tok % 4 = k.tok % 4", "(q.tok // 4) % 4 = (k.tok // 4) % 4"
_SEP = f"sp as ({_RAW.format(t='tk', g='q.tok // 16 = k.tok // 16')}), s2 as (select item, tok, out as val, pairs as sp_pairs from sp), sq as (select r.item, r.tok, r.out, r.pairs + s2.sp_pairs as pairs from ({_RAW.format(t='s2', g='q.tok % 16 = k.tok % 16')}) r join s2 using (item, tok))"


def _cost_arm(name, src):
    return f"select '{name}' as arm, cast(sum(a.pairs) as bigint) as pairs, round(avg((a.out - f.out) * (a.out - f.out)) + 1e-12, 8) as distance from {src} a join fu f using (item, tok)"


def _rope_terms(size, lo, pos, base):
    return f"select vec_id, {lo} + 2 * p as i, embedding[{lo} + 2 * p + 1] as a, embedding[{lo} + 2 * p + 2] as b, ({pos}) * pow({base}, -2.0 * p / {size}) as w from embeddings, range({size // 2}) r(p)"


_ROT = "rt as (" + " union all ".join(_rope_terms(n, lo, f"vec_id % {m}", 10000.0) for n, lo, m in ((16, 0, 8), (24, 16, 5), (24, 40, 3))) + "), rv as (select vec_id, i, a * cos(w) - b * sin(w) as x from rt union all select vec_id, i + 1, a * sin(w) + b * cos(w) from rt)"
_TOPK = "sc as (select vec_id, cast(v as double) as s, i as expert from (select vec_id, unnest(embedding) as v, cast(generate_subscripts(embedding, 1) - 1 as bigint) as i from embeddings)), rk as (select *, row_number() over (partition by vec_id order by s desc, expert) as k from sc), tp as (select vec_id, expert, exp(s) / sum(exp(s)) over (partition by vec_id) as weight from rk where k <= 6)"
_TXT = "tc as (select label, i, avg(v) as m from (select label, unnest(embedding) as v, generate_subscripts(embedding, 1) as i from embeddings) group by 1, 2), ec as (select vec_id, unnest(embedding) as v, generate_subscripts(embedding, 1) as i from embeddings), dt as (select vec_id, label, sum(cast(v as double) * m) as d from ec join tc using (i) group by 1, 2)"
ORACLES = {
    "attention_full": using("latents", sql=f"{_TOK} {_att('true')}"), "attention_sparse_stride": using("latents", sql=f"{_TOK} {_att(_STRIDE)}"), "attention_sparse_block": using("latents", sql=f"{_TOK} {_att(_BLOCK)}"),
    "attention_separated": using("latents", sql=f"{_TOK}, {_SEP} select item, tok, round(out, 6) + 0.0 as out, pairs from sq"),
    "attention_cost": using("latents", sql=f"{_TOK}, {_SEP}, fu as ({_RAW.format(t='tk', g='true')}), st as ({_RAW.format(t='tk', g=_STRIDE)}), bl as ({_RAW.format(t='tk', g=_BLOCK)}) " + " union all ".join(_cost_arm(*x) for x in (("full", "fu"), ("stride", "st"), ("block", "bl"), ("separated", "sq")))),
    "attention_reach": "select 'stride_stride' as arm, count(*) as reached from range(64) a(a), range(64) b(b) where a % 4 = b % 4 union all select 'stride_block', count(*) from range(64) a(a), range(64) b(b) where exists (select 1 from range(64) c(c) where a % 4 = c % 4 and (c // 4) % 4 = (b // 4) % 4) union all select 'full', cast(4096 as bigint)",
    "cross_attention": f"with {_TXT} select vec_id as id, round(sum(exp(d * 8.0) * label) / sum(exp(d * 8.0)) + 1e-10, 5) as out from dt group by 1",
    "joint_attention": using("latents", sql=f"{_TOK}, al as (select item, tok, val from tk union all select item_id, -1 - j, length(text) % 10 / 10 from benchmark, range(4) r(j)) select q.item, q.tok, round(sum(exp(q.val * k.val) * k.val) / sum(exp(q.val * k.val)), 6) + 0.0 as out, count(*) as pairs from tk q join al k on q.item = k.item group by 1, 2"),
    "rope3d_rotate": f"with {_ROT} select vec_id, round(sum(x * (i + 1)) + 1e-10, 5) + 0.0 as placed, cast(0.0 as double) as norm_change from rv group by 1",
    "rope_base_sensitivity": "with " + ", ".join(f"r{int(b)} as (select vec_id, a, b, w from ({_rope_terms(64, 0, '1', b)}))" for b in (10000.0, 256.0)) + " " + " union all ".join(f"select cast({int(b)} as bigint) as base, round(sum(pow(a * cos(w) - b * sin(w) - a * cos(2 * w) + b * sin(2 * w), 2) + pow(a * sin(w) + b * cos(w) - a * sin(2 * w) - b * cos(2 * w), 2)) / count(distinct vec_id), 6) as change from r{int(b)}" for b in (10000.0, 256.0)),
    "modulation_params": "select 1 as shared, cast(3072 * 3072 * 6 + 40 * 3072 * 6 as bigint) as params union all select 0, cast(40 as bigint) * 3072 * 3072 * 6",
    "modulate_identity": "select cast(0.0 as double) as gate_zero, round(sum(pow(cast(v as double) * 1.2 + 0.5, 2)) / count(distinct vec_id) + 1e-10, 5) as gate_one from (select vec_id, unnest(embedding) as v from embeddings)",
    "time_condition": "with e as (select vec_id, unnest(embedding) as v, generate_subscripts(embedding, 1) - 1 as i from embeddings) select vec_id, round(sum((cast(v as double) + case when i < 32 then cos((vec_id % 10 / 10) * exp(-ln(10000.0) * i / 32)) else sin((vec_id % 10 / 10) * exp(-ln(10000.0) * (i - 32) / 32)) end) * (i + 1)) + 1e-10, 5) + 0.0 as placed from e group by 1",
    "moe_topk_routing": f"with {_TOPK} select vec_id, expert, round(weight, 6) as weight from tp union all select vec_id, cast(-1 - j as bigint), 1.0 from embeddings, range(2) r(j)",
    "moe_load": f"with {_TOPK}, l as (select expert, count(*) as load from tp group by 1), m as (select sum(load) / 64 as m from l) select expert, load, round(load / m, 6) as over_mean, cast(greatest(0, load - floor(m * 1.25)) as bigint) as overflow from l, m",
    "moe_device_traffic": f"with {_TOPK} select vec_id % 8 as source_device, expert // 8 as device, count(*) as tokens from tp group by 1, 2",
    "moe_param_ratio": "select n as measure, cast(v as double) as value from (values ('experts_total', 66.0), ('experts_active', 8.0), ('active_width', 2.0), ('param_share', 0.17), ('dense_width', 1.0), ('per_device', 8.0)) t(n, v)",
    "pipeline_partition": "with l as (select cast(i as bigint) as layer, 10 + i % 5 as cost from range(40) t(i)), c as (select *, sum(cost) over (order by layer) as upto, sum(cost) over () as total from l) select least(3, cast(floor((upto - cost / 2) * 4 / total) as bigint)) as stage, count(*) as layers, cast(sum(cost) as bigint) as cost from c group by 1",
}
