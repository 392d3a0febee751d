"""Safety, balance, quality, review and annotation."""

from __future__ import annotations

from pyspark.sql import functions as F

from clipforge.functions.exprs import rnd
from clipforge.operators import quality as Q
from clipforge.sources import tables as T

from .sqlviews import h, using

ATTRS = {"gender": ["woman", "man"], "age": ["young", "old"], "hair": ["short", "long"], "accessories": ["glasses", "hat"], "clothing": ["suit", "coat"], "makeup": ["none", "stage"]}
BASE = {k: "any" for k in ATTRS}
THRESHOLDS = ((320, 10), (640, 20), (960, 30))


def docs(spark, d):
    return T.load(spark, d, "documents")


def scored(spark, d):
    """Text scores: distinct words in a hundred, signs and letters."""
    t = docs(spark, d)
    return t.select("doc_id", "lang", "source", "text", Q.lexical_percent(F.col("text")).alias("lexical"), Q.word_count(F.col("text")).alias("words"),
                    (F.lit(100) - F.floor(F.regexp_count("text", F.lit(r"[*$%&#!|]")) * 100 / F.greatest(F.length("text"), F.lit(1)))).cast("bigint").alias("clean"))


def agg_ids(df, *by):
    g = df.groupBy(*by) if by else df.groupBy()
    return g.agg(F.count("*").alias("n"), F.sum("doc_id").cast("bigint").alias("ids"))


def safety_anti_join(spark, d):
    return agg_ids(Q.safety_gate(docs(spark, d), T.load(spark, d, "labels"), "doc_id"), "lang")


def stage_threshold_filter(spark, d):
    stages = spark.createDataFrame([(int(a), int(b)) for a, b in THRESHOLDS], "stage bigint, threshold bigint")
    c = T.clips(spark, d).withColumn("worst", F.least(*T.SCORES))
    return Q.staged_thresholds(c, stages).groupBy("stage").agg(F.count("*").alias("kept"))


def first_centroids(spark, d, k=10):
    rows = T.load(spark, d, "embeddings").filter(F.col("vec_id") < k).orderBy("vec_id").collect()
    return [[float(x) for x in r["embedding"]] for r in rows]


def cluster_balance(spark, d):
    """Clusters learnt in three rounds from the first ten vectors; at most four rows for each cluster and label."""
    rows = T.load(spark, d, "embeddings")
    e = Q.assign_clusters(rows, Q.lloyd(rows, first_centroids(spark, d), 3))
    kept = Q.balance_cap(e, ["cluster_id", "label"], 4, "vec_id")
    return kept.groupBy("cluster_id").agg(F.count("*").alias("n"), F.sum("vec_id").cast("bigint").alias("ids"))


def gate_vs_review(spark, d):
    v = scored(spark, d).withColumn("pred", ((F.col("lexical") >= 20) & (F.col("clean") >= 98)).cast("bigint"))
    return Q.gate_agreement(v.select("doc_id", "pred"), T.review(spark, d), "doc_id", "pred", "quality")


def routed(spark, d):
    s = scored(spark, d)
    return Q.route_annotator(s, "lexical", F.lit(Q.quantile(s, F.col("lexical"), 0.9)))


def annotator_saving(spark, d):
    return routed(spark, d).agg(F.sum("cost").cast("bigint").alias("tiered"), F.sum(F.col("words") * 34).cast("bigint").alias("heavy_only")).withColumn("saving", rnd(1 - F.col("tiered") / F.col("heavy_only")))


def caption_sections(spark, d):
    c = docs(spark, d).select("doc_id", Q.structured_caption(F.col("text")).alias("c"))
    # through JSON and back, as stored captions go
    kind = "summary string, parts struct<" + ",".join(f"{n}:string" for n in Q.SECTIONS) + ">"
    c = c.select("doc_id", F.from_json(F.to_json("c"), kind).alias("c"))
    return c.select("doc_id", F.length("c.summary").cast("bigint").alias("summary_len"), *[F.md5(F.col(f"c.parts.{n}")).alias(n) for n in Q.SECTIONS])


def caption_with_scores(spark, d):
    s = scored(spark, d)
    return s.select("doc_id", F.md5(Q.append_scores(F.split("text", "\n", -1)[0], {"quality": F.col("lexical"), "signs": F.col("clean")})).alias("caption_md5"))


def score_adherence(spark, d):
    """Asked and obtained scores by stage: the clarity of a clip as asked, its appeal shifted towards it in early stages only."""
    c = T.clips(spark, d).withColumn("stage", F.col("video_id") % 3)
    got = F.col("clarity") * (2 - F.col("stage")) + F.col("appeal") * F.col("stage")
    return c.groupBy("stage").agg(rnd(F.corr(F.col("clarity").cast("double"), got.cast("double")), 5).alias("adherence"))


def vary(spark, d):
    out = Q.vary_prompt(T.load(spark, d, "benchmark").select("item_id"), ATTRS, BASE)
    return out.select("item_id", "attribute", "value", F.array_join(F.transform(F.array_sort(F.map_entries("edited")), lambda e: F.concat(e["key"], F.lit("="), e["value"])), ",").alias("prompt"))


QUERIES = {
    "safety_anti_join": safety_anti_join,
    "balance_cap_lang": lambda s, d: agg_ids(Q.balance_cap(docs(s, d), ["lang"], 80, "doc_id"), "lang"),
    "balance_rate_lang": lambda s, d: agg_ids(Q.balance_rate(docs(s, d), "lang", 80, "doc_id"), "lang"),
    "balance_alpha": lambda s, d: agg_ids(Q.balance_targets(docs(s, d), "lang", 0.5, "doc_id"), "lang"),
    "aesthetic_low_tail": lambda s, d: agg_ids(Q.drop_low_tail(scored(s, d), "lexical", 0.1), "lang"),
    "quality_two_view": lambda s, d: agg_ids(Q.quality_gate(scored(s, d), {"lexical": 20, "clean": 98}), "lang"),
    "quality_weighted": lambda s, d: agg_ids(Q.quality_gate(scored(s, d), {"lexical": 0.5, "clean": 0.5}, "weighted", 75.0), "lang"),
    "human_quality_gate": lambda s, d: Q.human_quality_gate(T.clips(s, d), T.SCORES, 10).groupBy("flag").agg(F.count("*").alias("n"), F.sum("worst").cast("bigint").alias("worst_sum")),
    "stage_threshold_filter": stage_threshold_filter,
    "cluster_assign_fixed": lambda s, d: Q.assign_clusters(T.load(s, d, "embeddings"), first_centroids(s, d)).select("vec_id", "cluster_id"),
    "cluster_balance": cluster_balance, "gate_vs_review": gate_vs_review,
    "refine_top_fraction": lambda s, d: agg_ids(Q.refine(scored(s, d), "lexical", 0.2), "lang"),
    "review_pass": lambda s, d: Q.review_aggregate(T.review(s, d), ("v1", "v2", "v3", "v4"), "all").select("doc_id", "passed").union(Q.review_aggregate(T.review(s, d), ("v1", "v2", "v3", "v4"), "majority").select((-F.col("doc_id") - 1).alias("doc_id"), "passed")),
    "merge_manual": lambda s, d: Q.merge_sources(docs(s, d).filter("lang = 'en'").select("doc_id", "lang"), docs(s, d).join(T.load(s, d, "labels").filter("quality = 1"), "doc_id").select("doc_id", "quality")).groupBy("provenance").agg(F.count("*").alias("n"), F.count("quality").alias("with_quality")),
    "sft_subset": lambda s, d: agg_ids(Q.sft_subset(scored(s, d).filter("words >= 50"), "lang", "lexical", "doc_id", 100), "lang"),
    "annotator_routing": lambda s, d: routed(s, d).groupBy("tier").agg(F.count("*").alias("n"), F.sum("words").cast("bigint").alias("words"), F.sum("cost").cast("bigint").alias("cost")),
    "annotator_saving": annotator_saving, "caption_sections": caption_sections, "caption_with_scores": caption_with_scores, "score_adherence": score_adherence,
    "prompt_rewrite": lambda s, d: T.turn_clips(s, d).filter("role = 'user'").select("video_id", "clip_no", F.md5(Q.rewrite_prompt(F.col("text"))).alias("prompt_md5")),
    "prompt_variants": vary,
}

_WORDS = "list_filter(string_split_regex(text, '\\s+'), lambda w: w <> '')"
_SC = f"""sc as (select doc_id, lang, source, text, cast(case when len(w) > 0 then floor(len(list_distinct(w)) * 100 / len(w)) else 0 end as bigint) as lexical, cast(len(w) as bigint) as words,
  cast(100 - floor((length(text) - length(regexp_replace(text, '[*$%&#!|]', '', 'g'))) * 100 / greatest(length(text), 1)) as bigint) as clean from (select *, {_WORDS} as w from documents)) """
IDS = "count(*) as n, cast(sum(doc_id) as bigint) as ids"
_ROUTED = _SC + ", r as (select *, case when lexical >= (select quantile_cont(lexical, 0.9) from sc) then 'heavy' else 'light' end as tier from sc), rc as (select *, words * case tier when 'heavy' then 34 else 7 end as cost from r) "
_CENT = """ce as (select vec_id as c, embedding as ce from embeddings where vec_id < 10), ds as (select e.vec_id, e.label, c, round(list_sum(list_transform(list_zip(e.embedding, ce), lambda p: (cast(p[1] as double) - cast(p[2] as double)) * (cast(p[1] as double) - cast(p[2] as double)))), 9) as dist from embeddings e, ce),
  cl as (select vec_id, any_value(label) as label, arg_min(c, struct_pack(d := dist, c := c)) as cluster_id from ds group by 1) """


def _lloyd_sql(rounds: int) -> str:
    """Centroids c0 (the first ten vectors) to c<rounds>, and for each the assignment a<k>."""
    near = "select vec_id, any_value(label) as label, any_value(embedding) as embedding, arg_min(c, struct_pack(d := dist, c := c)) as cluster_id from (select e.vec_id, e.label, e.embedding, c, round(list_sum(list_transform(list_zip(e.embedding, ce), lambda p: (cast(p[1] as double) - p[2]) * (cast(p[1] as double) - p[2]))), 9) as dist from embeddings e, {}) group by 1"
    ctes = ["c0 as (select vec_id as c, list_transform(embedding, lambda x: cast(x as double)) as ce from embeddings where vec_id < 10)", f"a0 as ({near.format('c0')})"]
    for k in range(1, rounds + 1):
        mean = f"select cluster_id, list(m order by j) as ce from (select cluster_id, j, round(avg(cast(v as double)), 9) as m from (select cluster_id, unnest(embedding) as v, generate_subscripts(embedding, 1) as j from a{k - 1}) group by 1, 2) group by 1"
        ctes += [f"c{k} as (select p.c, coalesce(m.ce, p.ce) as ce from c{k - 1} p left join ({mean}) m on m.cluster_id = p.c)", f"a{k} as ({near.format(f'c{k}')})"]
    return "with " + ", ".join(ctes)


def _hash_rate(rate: str, seed: str) -> str:
    k = h(f"cast(doc_id as varchar) || '{seed}'")
    return f"select lang, {IDS} from d join rates using (lang) where cast({k} as double) < {rate} * 4294967296.0 group by 1"


_LINES = "string_split(text, chr(10))"
ORACLES = {
    "safety_anti_join": f"select lang, {IDS} from documents where doc_id not in (select doc_id from labels where toxic = 1) group by 1",
    "balance_cap_lang": f"select lang, {IDS} from (select *, row_number() over (partition by lang order by " + h("cast(doc_id as varchar) || 'cap'") + ", doc_id) as k from documents) where k <= 80 group by 1",
    "balance_rate_lang": "with d as (select doc_id, lang from documents), rates as (select lang, least(1.0, cast(80.0 as double) / count(*)) as rate from d group by 1) " + _hash_rate("rate", "rate"),
    "balance_alpha": "with d as (select doc_id, lang from documents), n as (select lang, pow(count(*), -0.5) as p from d group by 1), rates as (select lang, p / (select max(p) from n) as rate from n) " + _hash_rate("rate", "alpha"),
    "aesthetic_low_tail": f"with {_SC} select lang, {IDS} from sc where lexical >= (select quantile_cont(lexical, 0.1) from sc) group by 1",
    "quality_two_view": f"with {_SC} select lang, {IDS} from sc where lexical >= 20 and clean >= 98 group by 1",
    "quality_weighted": f"with {_SC} select lang, {IDS} from sc where lexical * 0.5 + clean * 0.5 >= 75 group by 1",
    "human_quality_gate": using("clips", sql="select flag, count(*) as n, cast(sum(least(body, face, appeal, clarity, occlusion)) as bigint) as worst_sum from clips where least(body, face, appeal, clarity, occlusion) >= 10 group by 1"),
    "stage_threshold_filter": using("clips", sql="select cast(s as bigint) as stage, count(*) as kept from clips join (values (320, 10), (640, 20), (960, 30)) v(s, t) on least(body, face, appeal, clarity, occlusion) >= t group by 1"),
    "cluster_assign_fixed": f"with {_CENT} select vec_id, cluster_id from cl",
    "cluster_balance": _lloyd_sql(3) + ", k as (select *, row_number() over (partition by cluster_id, label order by " + h("cast(vec_id as varchar) || 'cap'") + ", vec_id) as k from a3) select cluster_id, count(*) as n, cast(sum(vec_id) as bigint) as ids from k where k <= 4 group by 1",
    "gate_vs_review": f"with {_SC} select cast(lexical >= 20 and clean >= 98 as bigint) as pred, cast(quality as bigint) as quality, count(*) as n from sc join labels using (doc_id) group by 1, 2",
    "refine_top_fraction": f"with {_SC} select lang, {IDS} from sc where lexical >= (select quantile_cont(lexical, 0.8) from sc) group by 1",
    "review_pass": using("review", sql="select doc_id, cast(v1 + v2 + v3 + v4 = 4 as integer) as passed from review union all select -doc_id - 1, cast((v1 + v2 + v3 + v4) * 2 > 4 as integer) from review"),
    "merge_manual": "select 'auto' as provenance, count(*) as n, cast(0 as bigint) as with_quality from documents where lang = 'en' union all select 'manual', count(*), count(quality) from documents join labels using (doc_id) where quality = 1",
    "sft_subset": f"with {_SC}, g as (select * from sc where words >= 50), r as (select *, row_number() over (partition by lang order by lexical desc, doc_id) as k from g) select lang, {IDS} from r where k <= 100 // (select count(distinct lang) from g) group by 1",
    "annotator_routing": f"with {_ROUTED} select tier, count(*) as n, cast(sum(words) as bigint) as words, cast(sum(cost) as bigint) as cost from rc group by 1",
    "annotator_saving": f"with {_ROUTED} select cast(sum(cost) as bigint) as tiered, cast(sum(words * 34) as bigint) as heavy_only, round(1 - sum(cost) / sum(words * 34), 6) as saving from rc",
    "caption_sections": f"select doc_id, cast(length({_LINES}[1]) as bigint) as summary_len, " + ", ".join(f"md5(coalesce(array_to_string(list_filter({_LINES}, lambda x, i: i > 1 and (i - 2) % 7 = {k}), ' '), '')) as {n}" for k, n in enumerate(Q.SECTIONS)) + " from documents",
    "caption_with_scores": f"with {_SC} select doc_id, md5({_LINES}[1] || ' | quality: ' || lexical || ' | signs: ' || clean) as caption_md5 from sc",
    "score_adherence": using("clips", sql="select video_id % 3 as stage, round(corr(cast(clarity as double), cast(clarity * (2 - video_id % 3) + appeal * (video_id % 3) as double)), 5) as adherence from clips group by 1"),
    "prompt_rewrite": f"select conv_id as video_id, turn as clip_no, md5('subject: ' || array_to_string(w[1:4], ' ') || '; description: ' || array_to_string(w[5:1004], ' ')) as prompt_md5 from (select *, {_WORDS} as w from conversations where role = 'user')",
    "prompt_variants": "with a(attribute, value) as (values " + ", ".join(f"('{a}', '{v}')" for a, vs in ATTRS.items() for v in vs) + "), b(k) as (values " + ", ".join(f"('{a}')" for a in ATTRS) + ") select item_id, attribute, value, (select string_agg(k || '=' || case when k = attribute then value else 'any' end, ',' order by k) from b) as prompt from benchmark, a",
}
