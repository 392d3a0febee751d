"""The relational surface that users of the methods need, one query each."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import key_int, rnd
from clipforge.operators import relational as R
from clipforge.sources import sinks
from clipforge.sources import tables as T
from clipforge.sources.scratch import materialize

from .sqlviews import h


def t(name):
    return lambda s, d: T.load(s, d, name)


ORD, LI, EV, CU, PA, DOC, SU, NA = (t(x) for x in ("orders", "lineitem", "events", "customer", "part", "documents", "supplier", "nation"))
money = lambda c: F.sum(F.col(c).cast("decimal(18,2)")).cast("double")


def joined(hint):
    def q(s, d):
        c = CU(s, d).select("c_custkey", "c_mktsegment")
        return ORD(s, d).join(c.hint(hint), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))
    return q


def asof(s, d):
    e = EV(s, d)
    right = e.filter("event_type = 'signup'").select("user_id", "ts", F.col("event_id").alias("last_signup"))
    return R.asof_join(e.filter("event_type = 'purchase'").select("user_id", "ts", "event_id"), right, "user_id", "ts", "last_signup").select("event_id", "last_signup")


def ranges(s, d):
    size = PA(s, d).select(F.col("p_partkey"), F.col("p_size").cast("bigint").alias("p"))
    bands = s.createDataFrame([("small", 1, 10), ("mid", 8, 30), ("large", 25, 50)], "band string, lo bigint, hi bigint")
    return R.range_join(size, bands, "p", "lo", "hi", 8).groupBy("band").agg(F.count("*").alias("n"), F.sum("p_partkey").cast("bigint").alias("keys"))


def intervals(s, d):
    l = LI(s, d).select(F.col("l_suppkey").alias("k"), F.unix_date(F.col("l_shipdate").cast("date")).cast("bigint").alias("a_lo"), F.floor("l_quantity").cast("bigint").alias("q"), F.col("l_orderkey").alias("oa"))
    a = l.withColumn("a_hi", F.col("a_lo") + F.col("q")).select("k", "a_lo", "a_hi", "oa")
    b = a.select("k", F.col("a_lo").alias("b_lo"), F.col("a_hi").alias("b_hi"), F.col("oa").alias("ob"))
    return R.interval_join(a, b, "k", 16).filter("oa < ob").groupBy("k").agg(F.count("*").alias("n"))


def lateral(s, d):
    c = CU(s, d).select("c_custkey")
    o = ORD(s, d).select("o_custkey", "o_orderkey", "o_totalprice")
    top = o.where(F.col("o_custkey") == F.col("c_custkey").outer()).select(F.max("o_totalprice").alias("largest"), F.count("o_orderkey").alias("n"))
    return c.lateralJoin(top).filter("n > 0").select("c_custkey", "largest", "n")


def partitioned(s, d):
    """Written by status, read back with one status: only its folder is listed."""

    base = materialize(s.range(1), "anchor").inputFiles()[0].rsplit("/", 1)[0] + "-parts"
    sinks.write_bucketed(ORD(s, d).select("o_orderkey", "o_orderstatus"), base, ["o_orderstatus"])
    return sinks.read_partition(s, base, "o_orderkey bigint, o_orderstatus string", "o_orderstatus = 'F'").agg(F.count("*").alias("n"), F.sum("o_orderkey").cast("bigint").alias("keys"))


def recursive(s, d):
    """Customers of a nation chained by key: the depth at which each is reached, by a recursive query."""
    NA(s, d).createOrReplaceTempView("cf_nation")
    return s.sql("with recursive w(k, depth) as (select cast(0 as bigint), 0 union all select cast(n_nationkey as bigint), depth + 1 from w join cf_nation on n_nationkey = k + n_regionkey + 1 where depth < 30) select k, min(depth) as depth from w group by k")


def outer(s, d):
    a = CU(s, d).select("c_nationkey").filter("c_nationkey < 15").groupBy("c_nationkey").agg(F.count("*").alias("customers"))
    b = SU(s, d).select("s_nationkey").filter("s_nationkey >= 10").groupBy("s_nationkey").agg(F.count("*").alias("suppliers"))
    return a.join(b, a.c_nationkey == b.s_nationkey, "full").select(F.coalesce("c_nationkey", "s_nationkey").alias("nation"), F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


def by_price():
    return W.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")


dec = lambda c: F.col(c).cast("decimal(18,2)")
def ranking(orders):
    return orders.select("o_orderkey", F.row_number().over(by_price()).alias("rn"), F.rank().over(W.partitionBy("o_custkey").orderBy("o_orderstatus")).alias("rk"), F.dense_rank().over(W.partitionBy("o_custkey").orderBy("o_orderstatus")).alias("dr"), F.ntile(4).over(by_price()).alias("nt"), rnd(F.percent_rank().over(by_price())).alias("pr"), rnd(F.cume_dist().over(by_price())).alias("cd"))


def analytic(orders):
    return orders.select("o_orderkey", F.lag("o_orderkey").over(by_price()).alias("before"), F.lead("o_orderkey", 2).over(by_price()).alias("after2"), F.first("o_orderkey").over(by_price()).alias("first"), F.nth_value("o_orderkey", 2).over(by_price().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("second"))


QUERIES = {
    "scan_parquet_pruned": lambda s, d: ORD(s, d).filter("o_totalprice > 100000").agg(F.count("*").alias("n"), F.sum("o_orderkey").cast("bigint").alias("keys")),
    "scan_partitioned": partitioned,
    "filter_compound": lambda s, d: ORD(s, d).filter(F.col("o_totalprice").between(10_000, 90_000) & F.col("o_orderstatus").isin("F", "O") & F.col("o_orderpriority").rlike("^[12]") & ~F.col("o_orderstatus").eqNullSafe("P")).agg(F.count("*").alias("n")),
    "join_broadcast": joined("broadcast"), "join_sort_merge": joined("merge"), "join_shuffle_hash": joined("shuffle_hash"),
    "join_outer": outer,
    "join_semi": lambda s, d: CU(s, d).join(ORD(s, d).filter("o_orderstatus = 'P'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"),
    "join_anti": lambda s, d: CU(s, d).join(ORD(s, d), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"),
    "join_theta": lambda s, d: NA(s, d).select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("ra")).join(NA(s, d).select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("rb")), F.col("ra") < F.col("rb")).agg(F.count("*").alias("n")),
    "join_range": ranges, "join_interval": intervals, "join_asof": asof, "join_lateral": lateral,
    "join_salted": lambda s, d: R.salted_join(LI(s, d).select("l_orderkey", "l_partkey", "l_linenumber"), PA(s, d).select(F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey").groupBy("p_brand").agg(F.count("*").alias("n")),
    "agg_group": lambda s, d: LI(s, d).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), money("l_extendedprice").alias("price"), F.min("l_quantity").alias("least"), F.max("l_quantity").alias("most")),
    "agg_distinct": lambda s, d: LI(s, d).groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers")),
    "agg_having": lambda s, d: ORD(s, d).groupBy("o_custkey").agg(F.count("*").alias("n")).filter("n >= 15"),
    "agg_rollup": lambda s, d: ORD(s, d).rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().cast("bigint").alias("level")),
    "agg_cube": lambda s, d: ORD(s, d).cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().cast("bigint").alias("level")),
    "agg_grouping_sets": lambda s, d: ORD(s, d).groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")),
    "agg_pivot": lambda s, d: EV(s, d).groupBy((F.col("user_id") % 10).alias("k")).pivot("event_type", ["click", "error", "purchase", "signup", "view"]).agg(F.count("event_id")).na.fill(0),
    "agg_percentile": lambda s, d: EV(s, d).groupBy("event_type").agg(rnd(F.percentile("value", F.lit(0.5))).alias("median"), F.min_by("event_id", F.struct("value", "event_id")).alias("least"), F.count_if(F.col("value") > 100).alias("large")),
    "agg_approx": lambda s, d: EV(s, d).groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.approx_percentile("value", F.lit(0.5)).alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("hll_users")),
    "win_ranking": lambda s, d: ranking(ORD(s, d)),
    "win_analytic": lambda s, d: analytic(ORD(s, d)),
    "win_rows": lambda s, d: EV(s, d).select("event_id", F.sum(dec("value")).over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)).cast("double").alias("last3")),
    "win_range": lambda s, d: PA(s, d).select("p_partkey", F.count("*").over(W.partitionBy("p_brand").orderBy("p_size").rangeBetween(-5, 5)).alias("near")),
    "win_running": lambda s, d: EV(s, d).select("event_id", F.sum(dec("value")).over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)).cast("double").alias("running")),
    "sort_global": lambda s, d: SU(s, d).orderBy(F.desc("s_acctbal"), "s_suppkey").select("s_suppkey"),
    "topk": lambda s, d: ORD(s, d).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey"),
    "topk_per_group": lambda s, d: ORD(s, d).withColumn("k", F.row_number().over(W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey"))).filter("k <= 3").select("o_orderpriority", "o_orderkey", "k"),
    "limit_offset": lambda s, d: SU(s, d).orderBy("s_suppkey").offset(10).limit(15).select("s_suppkey"),
    "set_union": lambda s, d: CU(s, d).select(F.col("c_nationkey").alias("k")).union(SU(s, d).select("s_nationkey")).distinct(),
    "set_intersect": lambda s, d: CU(s, d).filter("c_nationkey < 18").select(F.col("c_nationkey").alias("k")).intersect(SU(s, d).select("s_nationkey")),
    "set_except": lambda s, d: CU(s, d).select(F.col("c_nationkey").alias("k")).exceptAll(SU(s, d).select("s_nationkey")).groupBy("k").agg(F.count("*").alias("n")),
    "fn_string": lambda s, d: DOC(s, d).select("doc_id", F.regexp_count("text", F.lit("the")).cast("bigint").alias("the_n"), F.regexp_extract("text", r"([A-Z]\w+)", 1).alias("first_cap"), F.translate(F.substring("text", 1, 12), "aeiou", "12345").alias("coded"), F.levenshtein("source", "lang").cast("bigint").alias("dist"), F.concat_ws("-", "lang", "source").alias("tag"), F.sha2("text", 256).alias("sha")),
    "fn_date": lambda s, d: ORD(s, d).select("o_orderkey", F.date_trunc("month", F.col("o_orderdate").cast("timestamp")).cast("date").cast("string").alias("month"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("bigint").alias("days"), F.dayofyear("o_orderdate").cast("bigint").alias("doy"), F.add_months(F.col("o_orderdate").cast("date"), 1).cast("string").alias("next")),
    "fn_math": lambda s, d: SU(s, d).select("s_suppkey", F.floor("s_acctbal").cast("bigint").alias("f"), F.ceil("s_acctbal").cast("bigint").alias("c"), rnd(F.sqrt(F.abs("s_acctbal"))).alias("r"), rnd(F.ln(F.abs("s_acctbal") + 1)).alias("l"), F.pmod(F.floor("s_acctbal"), F.lit(7)).cast("bigint").alias("m"), rnd(F.pow(F.col("s_suppkey") % 10, F.lit(3))).alias("p")),
    "fn_array": lambda s, d: T.load(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("positive"), rnd(F.array_max("embedding").cast("double")).alias("top"), F.array_position(F.transform("embedding", lambda x: x == F.array_max("embedding")), True).cast("bigint").alias("at"), rnd(F.aggregate(F.slice("embedding", 1, 8), F.lit(0.0), lambda a, x: a + x.cast("double"))).alias("head")),
    "fn_map": lambda s, d: EV(s, d).groupBy("user_id").agg(F.map_from_entries(F.array_sort(F.collect_set(F.struct("event_type", F.length("event_type"))))).alias("m")).select("user_id", F.size("m").cast("bigint").alias("kinds"), F.array_join(F.map_keys(F.map_filter("m", lambda k, v: v > 4)), ",").alias("long_kinds")),
    "fn_json": lambda s, d: EV(s, d).select("event_id", F.from_json("props", "k bigint")["k"].alias("k"), F.get_json_object("props", "$.k").alias("k_text"), F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k_variant")),
    "subquery_exists": lambda s, d: CU(s, d).where(ORD(s, d).where((F.col("o_custkey") == F.col("c_custkey").outer()) & (F.col("o_totalprice") > 200_000)).exists()).select("c_custkey"),
    "subquery_scalar": lambda s, d: ORD(s, d).where(F.col("o_totalprice") > ORD(s, d).select(F.avg("o_totalprice") * 1.5).scalar()).select("o_orderkey"),
    "sample_hash": lambda s, d: R.hash_sample(DOC(s, d), F.col("doc_id"), 200).select("doc_id"),
    "sample_stratified": lambda s, d: DOC(s, d).withColumn("k", F.row_number().over(W.partitionBy("lang").orderBy(key_int(F.col("doc_id")), "doc_id"))).filter("k <= 10").select("lang", "doc_id"),
    "recursive_walk": recursive,
}

_JOIN = "select c_mktsegment, count(*) as n from orders join customer on o_custkey = c_custkey group by 1"
ORACLES = {
    "scan_parquet_pruned": "select count(*) as n, cast(sum(o_orderkey) as bigint) as keys from orders where o_totalprice > 100000",
    "scan_partitioned": "select count(*) as n, cast(sum(o_orderkey) as bigint) as keys from orders where o_orderstatus = 'F'",
    "filter_compound": "select count(*) as n from orders where o_totalprice between 10000 and 90000 and o_orderstatus in ('F', 'O') and regexp_matches(o_orderpriority, '^[12]') and o_orderstatus is distinct from 'P'",
    "join_broadcast": _JOIN, "join_sort_merge": _JOIN, "join_shuffle_hash": _JOIN,
    "join_outer": "with a as (select c_nationkey, count(*) as customers from customer where c_nationkey < 15 group by 1), b as (select s_nationkey, count(*) as suppliers from supplier where s_nationkey >= 10 group by 1) select coalesce(c_nationkey, s_nationkey) as nation, coalesce(customers, 0) as customers, coalesce(suppliers, 0) as suppliers from a full join b on c_nationkey = s_nationkey",
    "join_semi": "select c_custkey from customer where c_custkey in (select o_custkey from orders where o_orderstatus = 'P')",
    "join_anti": "select c_custkey from customer where c_custkey not in (select o_custkey from orders)",
    "join_theta": "select count(*) as n from nation a join nation b on a.n_regionkey < b.n_regionkey",
    "join_range": "select band, count(*) as n, cast(sum(p_partkey) as bigint) as keys from part join (values ('small', 1, 10), ('mid', 8, 30), ('large', 25, 50)) b(band, lo, hi) on p_size between lo and hi group by 1",
    "join_interval": "with a as (select l_suppkey as k, cast(l_shipdate as date) as lo, cast(l_shipdate as date) + cast(floor(l_quantity) as integer) as hi, l_orderkey as o from lineitem) select x.k, count(*) as n from a x join a y on x.k = y.k and x.lo <= y.hi and y.lo <= x.hi and x.o < y.o group by 1",
    "join_asof": "select a.event_id, (select b.event_id from events b where b.event_type = 'signup' and b.user_id = a.user_id and b.ts <= a.ts order by b.ts desc limit 1) as last_signup from events a where a.event_type = 'purchase'",
    "join_lateral": "select o_custkey as c_custkey, max(o_totalprice) as largest, count(*) as n from orders join customer on c_custkey = o_custkey group by 1",
    "join_salted": "select p_brand, count(*) as n from lineitem join part on l_partkey = p_partkey group by 1",
    "agg_group": "select l_returnflag, l_linestatus, count(*) as n, cast(sum(cast(l_extendedprice as decimal(18,2))) as double) as price, min(l_quantity) as least, max(l_quantity) as most from lineitem group by 1, 2",
    "agg_distinct": "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem group by 1",
    "agg_having": "select o_custkey, count(*) as n from orders group by 1 having count(*) >= 15",
    "agg_rollup": "select o_orderstatus, o_orderpriority, count(*) as n, cast(grouping_id(o_orderstatus, o_orderpriority) as bigint) as level from orders group by rollup (o_orderstatus, o_orderpriority)",
    "agg_cube": "select o_orderstatus, o_orderpriority, count(*) as n, cast(grouping_id(o_orderstatus, o_orderpriority) as bigint) as level from orders group by cube (o_orderstatus, o_orderpriority)",
    "agg_grouping_sets": "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())",
    "agg_pivot": "select user_id % 10 as k, " + ", ".join(f"count(*) filter (event_type = '{e}') as {e}" for e in ("click", "error", "purchase", "signup", "view")) + " from events group by 1",
    "agg_percentile": "select event_type, round(quantile_cont(value, 0.5), 6) as median, arg_min(event_id, struct_pack(v := value, e := event_id)) as least, count(*) filter (value > 100) as large from events group by 1",
    "win_ranking": "select o_orderkey, cast(row_number() over c as integer) as rn, cast(rank() over (partition by o_custkey order by o_orderstatus) as integer) as rk, cast(dense_rank() over (partition by o_custkey order by o_orderstatus) as integer) as dr, cast(ntile(4) over c as integer) as nt, round(percent_rank() over c, 6) as pr, round(cume_dist() over c, 6) as cd from orders window c as (partition by o_custkey order by o_totalprice, o_orderkey)",
    "win_analytic": "select o_orderkey, lag(o_orderkey) over c as before, lead(o_orderkey, 2) over c as after2, first_value(o_orderkey) over c as first, nth_value(o_orderkey, 2) over (partition by o_custkey order by o_totalprice, o_orderkey rows between unbounded preceding and unbounded following) as second from orders window c as (partition by o_custkey order by o_totalprice, o_orderkey)",
    "win_rows": "select event_id, cast(sum(cast(value as decimal(18,2))) over (partition by user_id order by ts, event_id rows between 2 preceding and current row) as double) as last3 from events",
    "win_range": "select p_partkey, count(*) over (partition by p_brand order by p_size range between 5 preceding and 5 following) as near from part",
    "win_running": "select event_id, cast(sum(cast(value as decimal(18,2))) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row) as double) as running from events",
    "sort_global": "select s_suppkey from supplier", "topk": "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 20",
    "topk_per_group": "select o_orderpriority, o_orderkey, cast(k as integer) as k from (select *, row_number() over (partition by o_orderpriority order by o_totalprice desc, o_orderkey) as k from orders) where k <= 3",
    "limit_offset": "select s_suppkey from supplier order by 1 limit 15 offset 10",
    "set_union": "select c_nationkey as k from customer union select s_nationkey from supplier",
    "set_intersect": "select c_nationkey as k from customer where c_nationkey < 18 intersect select s_nationkey from supplier",
    "set_except": "select k, count(*) as n from (select c_nationkey as k from customer except all select s_nationkey from supplier) group by 1",
    "fn_string": r"select doc_id, cast(len(string_split(text, 'the')) - 1 as bigint) as the_n, regexp_extract(text, '([A-Z][0-9A-Za-z_]+)', 1) as first_cap, translate(substr(text, 1, 12), 'aeiou', '12345') as coded, cast(levenshtein(source, lang) as bigint) as dist, lang || '-' || source as tag, sha256(text) as sha from documents",
    "fn_date": "select o_orderkey, cast(cast(date_trunc('month', o_orderdate) as date) as varchar) as month, date_diff('day', date '1995-01-01', cast(o_orderdate as date)) as days, dayofyear(o_orderdate) as doy, cast(cast(cast(o_orderdate as date) + interval 1 month as date) as varchar) as next from orders",
    "fn_math": "select s_suppkey, cast(floor(s_acctbal) as bigint) as f, cast(ceil(s_acctbal) as bigint) as c, round(sqrt(abs(s_acctbal)), 6) as r, round(ln(abs(s_acctbal) + 1), 6) as l, (cast(floor(s_acctbal) as bigint) % 7 + 7) % 7 as m, round(pow(s_suppkey % 10, 3), 6) as p from supplier",
    "fn_array": "select vec_id, cast(len(list_filter(embedding, lambda x: x > 0)) as bigint) as positive, round(cast(list_max(embedding) as double), 6) as top, cast(list_position(embedding, list_max(embedding)) as bigint) as at, round(list_sum(list_transform(embedding[1:8], lambda x: cast(x as double))), 6) + 0.0 as head from embeddings",
    "fn_map": "select user_id, count(distinct event_type) as kinds, coalesce(string_agg(distinct event_type, ',' order by event_type) filter (length(event_type) > 4), '') as long_kinds from events group by 1",
    "fn_json": "select event_id, cast(json_extract_string(props, '$.k') as bigint) as k, json_extract_string(props, '$.k') as k_text, cast(json_extract_string(props, '$.k') as bigint) as k_variant from events",
    "subquery_exists": "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 200000)",
    "subquery_scalar": "select o_orderkey from orders where o_totalprice > (select avg(o_totalprice) * 1.5 from orders)",
    "sample_hash": "select doc_id from documents where " + h("cast(doc_id as varchar)") + " % 1000 < 200",
    "sample_stratified": "select lang, doc_id from (select *, row_number() over (partition by lang order by " + h("cast(doc_id as varchar)") + ", doc_id) as k from documents) where k <= 10",
    "recursive_walk": "with recursive w(k, depth) as (select cast(0 as bigint), 0 union all select cast(n_nationkey as bigint), depth + 1 from w join nation on n_nationkey = k + n_regionkey + 1 where depth < 30) select k, min(depth) as depth from w group by k",
}
