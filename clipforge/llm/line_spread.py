"""Line dedup by the spread of a line over distinct sites.

Lines are told apart by a 128-bit hash of their trimmed text. A HyperLogLog
sketch of the sites is kept per hash and merged by aggregation. Lines whose
estimate lies clearly at or above ``min_sites`` are boilerplate; only those near
the threshold get an exact distinct count. Boilerplate lines are then removed
from every document, whole texts throughout.

Null texts count as empty; blank lines are never removed and never counted. A
null site is one site. Rows that repeat add no site and are each cleaned. An
empty table gives no rows. Other columns pass through ``clean_documents``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import marked_likely, materialize, table

MIN_SITES = 10
LG_K = 12
#: Width of the band that is counted exactly, in standard errors of the sketch, and at least one site.
BAND = 6


def _key(c: Column, name: str) -> list[Column]:
    return [F.xxhash64(c).alias(f"{name}1"), F.xxhash64(F.lit(17), c).alias(f"{name}2")]


def _lines(docs: DataFrame) -> DataFrame:
    """A row for each line that is not blank: its hash, the site, its text's hash and its place."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select(text.alias("text"), F.coalesce(F.col("site").cast("string"), F.lit("\x00")).alias("site"))
    rows = rows.select("site", *_key(F.col("text"), "t"), F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
    rows = rows.withColumn("line", F.trim("line")).filter("line <> ''")
    return rows.select("site", "t1", "t2", "pos", *_key(F.col("line"), "h"))


def boilerplate(docs: DataFrame, min_sites: int = MIN_SITES, lg_k: int = LG_K) -> DataFrame:
    """Hashes (h1, h2) of the lines that stand on at least ``min_sites`` sites. ``docs`` has text and site."""
    lines = _lines(docs)
    margin = max(1.0, BAND * 1.04 / (2 ** (lg_k / 2)) * min_sites)
    spread = lines.groupBy("h1", "h2").agg(F.hll_sketch_estimate(F.hll_sketch_agg("site", F.lit(lg_k))).alias("sites"))
    spread = materialize(spread.filter(F.col("sites") >= min_sites - margin), "line-spread")
    near = spread.filter(F.col("sites") < min_sites + margin).select("h1", "h2")
    exact = lines.join(near, ["h1", "h2"], "left_semi").select("h1", "h2", "site").distinct().groupBy("h1", "h2").agg(F.count("*").alias("sites")).filter(F.col("sites") >= min_sites)
    return materialize(spread.filter(F.col("sites") >= min_sites + margin).select("h1", "h2").unionByName(exact.select("h1", "h2")), "boilerplate")


def clean_documents(docs: DataFrame, site: Column, min_sites: int = MIN_SITES) -> DataFrame:
    """``docs`` with ``clean_text``, ``n_lines`` (not blank) and ``n_removed`` added (columns of these names are replaced)."""
    sited = docs.select("text", site.alias("site"))
    lines = _lines(sited)
    # equal texts lose the same lines, so one list of places serves all rows of a text
    places = lines.join(boilerplate(sited, min_sites), ["h1", "h2"], "left_semi").groupBy("t1", "t2").agg(F.sort_array(F.collect_set("pos")).alias("gone"))
    places = materialize(places, "boilerplate-places")
    text = F.coalesce(F.col("text"), F.lit(""))
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns])  # so that no column meets one of the same name
    keyed = docs.select(row.alias("row"), text.alias("body"), F.xxhash64(text).alias("k1"), F.xxhash64(F.lit(17), text).alias("k2"))
    # only texts that may lose a line meet the list; the others stay where they are
    marked = marked_likely(keyed, F.col("k1"), places, F.col("t1"), "likely")
    met = marked.filter("likely").join(places, (F.col("k1") == F.col("t1")) & (F.col("k2") == F.col("t2")), "left").select("row", "body", "gone")
    joined = met.unionByName(marked.filter("not likely").select("row", "body", F.lit(None).cast("array<int>").alias("gone")))
    cut = F.split("body", "\n", -1)
    gone = F.coalesce(F.col("gone"), F.array().cast("array<int>"))
    joined = joined.select("row", "body", gone.alias("gone"), cut.alias("cut"))

    def between(k: Column) -> Column:
        """The lines after the (k-1)th removed one and before the kth."""
        first = F.when(k == 0, 0).otherwise(F.get("gone", k - 1) + 1)
        return F.slice("cut", first + 1, F.coalesce(F.get("gone", k), F.size("cut")) - first)

    kept = F.flatten(F.transform(F.sequence(F.lit(0), F.size("gone")), between))
    clean = F.when(F.size("gone") == 0, F.col("body")).otherwise(F.array_join(kept, "\n"))
    counted = F.size(F.filter("cut", lambda x: F.trim(x) != ""))
    added = {"clean_text": clean, "n_lines": counted, "n_removed": F.size("gone")}
    done = joined.select("row", *[v.alias(k) for k, v in added.items()])
    return done.select(*[F.col("row")[c].alias(c) for c in docs.columns if c not in added], *added)


def op8_line_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), "text", "source")
    out = clean_documents(docs, F.col("source"))
    return out.select("doc_id", "n_lines", "n_removed", F.md5("clean_text").alias("clean_md5"))


ORACLE = f"""
with cut as (
  select doc_id, source, coalesce(text, '') as text, unnest(string_split(coalesce(text, ''), chr(10))) as line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) as pos
  from documents),
spread as (select trim(line) as line, count(distinct coalesce(source, chr(0))) as sites from cut where trim(line) <> '' group by 1),
marked as (select c.doc_id, c.pos, c.line, trim(c.line) <> '' as full_, coalesce(s.sites >= {MIN_SITES}, false) as gone from cut c left join spread s on trim(c.line) = s.line)
select doc_id, cast(count(*) filter (full_) as integer) as n_lines, cast(count(*) filter (gone) as integer) as n_removed,
  md5(coalesce(string_agg(line, chr(10) order by pos) filter (not gone), '')) as clean_md5
from marked group by doc_id
"""
