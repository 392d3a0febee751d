"""Shot splitting, cropping and motion."""

from __future__ import annotations

from pyspark.sql import functions as F

from clipforge.functions.exprs import rnd
from clipforge.operators import scene as S
from clipforge.plans import funnel as P
from clipforge.sources import tables as T

from .sqlviews import using

HARD, GRADUAL, HALF, TOL = 150.0, 150.0, 3, 3


def cut_rows(split):
    return lambda s, d: split(T.frames(s, d)).filter("cut").select("media_id", "frame_no")


def agreement(spark, d):
    """F1 of both splitters on hard and on ramped cuts, over a grid of thresholds."""
    out = None
    for kind in ("hard", "ramp"):
        f = T.frames_planted(spark, d, ramp=kind == "ramp")
        truth = f.filter("true_cut")
        for method, t, cuts in (("delta", 150, S.split_by_delta(f, 150.0)), ("delta", 100, S.split_by_delta(f, 100.0)), ("gradual", 150, S.split_gradual(f, 150.0)), ("gradual", 120, S.split_gradual(f, 120.0))):
            row = S.boundary_f1(cuts.filter("cut"), truth, TOL).select(F.lit(kind).alias("kind"), F.lit(method).alias("method"), F.lit(t).cast("bigint").alias("threshold"), "n_pred", "n_true", *[rnd(F.col(c)).alias(c) for c in ("precision", "recall", "f1")])
            out = row if out is None else out.unionByName(row)
    return out


def text_share(spark, d):
    p = T.load(spark, d, "pages").select("page_id", F.length(S.visible_text(F.col("html"))).cast("bigint").alias("visible"), F.length("html").cast("bigint").alias("total"))
    return p.withColumn("keep", (F.col("visible") * 10 <= F.col("total") * 7).cast("int"))


def band_crop(spark, d):
    lines = S.crop_text_bands(T.text_clips(spark, d), F.lower("line").rlike("licen|rights reserved"))
    return lines.groupBy("doc_id").agg(F.count("*").alias("n"), F.sum("len").cast("bigint").alias("chars"))


def block_flow(cells):
    return S.block_flow(cells).select("item", "t", "block_y", "block_x", F.col("dy").cast("bigint").alias("dy"), F.col("dx").cast("bigint").alias("dx"))


@P.register("split_lines")
def _split_lines(text: str = "text") -> P.Op:
    lines = F.posexplode(F.split(F.col(text), "\n", -1)).alias("pos", "line")
    return P.Op("split_lines", run=lambda df: df.select("doc_id", lines).select("doc_id", F.col("pos").cast("bigint").alias("clip_no"), "line"))


@P.register("blank_border")
def _blank_border() -> P.Op:
    return P.Op("blank_border", run=S.crop_blank_border, after=("split_lines",))


@P.register("caption_bands")
def _caption_bands(band: int = 2, pattern: str = "licen|rights reserved") -> P.Op:
    return P.Op("caption_bands", run=lambda df: S.crop_text_bands(df, F.lower("line").rlike(pattern), band), after=("split_lines", "blank_border"))


@P.register("text_limit")
def _text_limit(percent: int = 2) -> P.Op:
    return P.Op("text_limit", run=lambda df: S.limit_signs(df, percent), after=("split_lines", "blank_border", "caption_bands"))


#: Crops go from split to border to captions to the text filter, in whatever order a configuration lists them.
CROPS = {"ops": [{"op": "text_limit", "percent": 2}, {"op": "caption_bands", "band": 2}, {"op": "blank_border"}, {"op": "split_lines"}]}


def crop_chain(spark, d):
    out = P.build_pipeline(CROPS).in_order().run(T.load(spark, d, "documents"))
    return out.groupBy("doc_id").agg(F.count("*").alias("lines"), F.sum(F.length("line")).cast("bigint").alias("chars"))


QUERIES = {
    "crop_chain": crop_chain,
    "scene_delta_cuts": cut_rows(lambda f: S.split_by_delta(f, HARD)),
    "scene_gradual_cuts": lambda s, d: S.split_gradual(T.frames_planted(s, d, ramp=True), GRADUAL, HALF).filter("cut").select("media_id", "frame_no"),
    "scene_flash_suppressed": cut_rows(lambda f: S.suppress_flash(S.split_by_delta(f, HARD))),
    "scene_clips": lambda s, d: S.clips_from_cuts(S.split_by_delta(T.frames(s, d), HARD)),
    "scene_method_agreement": agreement,
    "scene_gap_sessions": lambda s, d: S.with_clip_no(S.split_by_gap(T.frames(s, d), 7200)).groupBy("media_id", "clip_no").agg(F.count("*").alias("n"), F.sum("texture").cast("bigint").alias("texture")),
    "crop_dark_border": lambda s, d: S.border_box(T.latents(s, d, "88"), 0.15),
    "crop_line_bands": band_crop,
    "page_band_crop": lambda s, d: T.load(s, d, "pages").select("page_id", F.length(S.strip_bands(F.col("html"))).cast("bigint").alias("kept_chars")),
    "text_share_filter": text_share,
    "motion_score": lambda s, d: S.motion_score(T.frames(s, d)).select("media_id", "n", rnd(F.col("per_frame") + 1e-9, 4).alias("per_frame"), rnd(F.col("per_second") + 1e-10, 6).alias("per_second")),
    "motion_band_filter": lambda s, d: S.motion_band(S.motion_score(T.frames(s, d)).select("media_id", rnd(F.col("per_frame") + 1e-9, 4).alias("per_frame"))),
    "motion_block_flow": lambda s, d: block_flow(T.latents(s, d)),
}

_LAG = "lag(luma) over (partition by media_id order by frame_no)"
_FLASH = """c as (select media_id, frame_no, luma, coalesce(abs(luma - lag(luma) over w) > 150, false) as cut, lag(luma) over w as before, lead(luma, 1) over w as n1, lead(luma, 2) over w as n2 from frames window w as (partition by media_id order by frame_no)),
  f as (select *, cut and (coalesce(abs(n1 - before) <= 60, false) or coalesce(abs(n2 - before) <= 60, false)) as flash from c) """


def _gradual(view: str, name: str, t: float) -> str:
    return f"""{name}_j as (select media_id, frame_no, round(abs((luma + a1 + a2) / 3 - (b1 + b2 + b3) / 3), 9) as jump from (select media_id, frame_no, luma, lead(luma, 1) over w as a1, lead(luma, 2) over w as a2,
      lag(luma, 1) over w as b1, lag(luma, 2) over w as b2, lag(luma, 3) over w as b3 from {view} window w as (partition by media_id order by frame_no))),
    {name}_k as (select media_id, frame_no, coalesce(jump, 0.0) as jump from {name}_j),
    {name} as (select media_id, frame_no from (select *, coalesce(lag(jump) over w, 0.0) as p, coalesce(lead(jump) over w, 0.0) as n from {name}_k window w as (partition by media_id order by frame_no)) where jump > {t} and jump >= p and jump > n)"""


def _agreement_sql() -> str:
    ctes, rows = [], []
    for kind in ("hard", "ramp"):
        for method, t in (("delta", 150), ("delta", 100), ("gradual", 150), ("gradual", 120)):
            n = f"{kind}_{method}_{t}"
            ctes.append(_gradual(f"planted_{kind}", n, t) if method == "gradual" else f"{n} as (select media_id, frame_no from (select *, abs(luma - {_LAG}) as s from planted_{kind}) where s > {t})")
            true = f"(select media_id, frame_no from planted_{kind} where true_cut)"
            near = "exists (select 1 from {} b where b.media_id = a.media_id and b.frame_no between a.frame_no - 3 and a.frame_no + 3)"
            rows.append(f"select '{kind}' as kind, '{method}' as method, cast({t} as bigint) as threshold, (select count(*) from {n}) as n_pred, (select count(*) from {true}) as n_true, (select count(*) from {n} a where {near.format(true)}) as hp, (select count(*) from {true} a where {near.format(n)}) as hq")
    return using("planted_hard", "planted_ramp", sql=f"""{', '.join(ctes)}, r as ({' union all '.join(rows)}), m as (select kind, method, threshold, n_pred, n_true, hp / n_pred as p, hq / n_true as q from r)
      select kind, method, threshold, n_pred, n_true, round(p, 6) as precision, round(q, 6) as recall, round(2 * p * q / (p + q), 6) as f1 from m""")


_SCORE = """m as (select media_id, count(*) as n, coalesce(avg(s), 0.0) as pf, case when max(ts) > min(ts) then sum(s) / ((epoch_us(max(ts)) - epoch_us(min(ts))) / 1000000.0) else 0.0 end as ps
  from (select *, abs(luma - lag(luma) over (partition by media_id order by frame_no)) as s from frames) group by 1) """
_VIS = r"regexp_replace(regexp_replace(regexp_replace(html, '(?s)<script[^>]*>.*?</script>', '', 'g'), '(?s)<style[^>]*>.*?</style>', '', 'g'), '(?s)<[^>]*>', '', 'g')"
_BAND = "regexp_replace(regexp_replace(regexp_replace(html, '(?s)<head>.*?</head>', '', 'g'), '(?s)<nav>.*?</nav>', '', 'g'), '(?s)<footer>.*?</footer>', '', 'g')"
ORACLES = {
    "scene_delta_cuts": using("frames", sql=f"select media_id, frame_no from (select *, abs(luma - {_LAG}) as s from frames) where s > 150"),
    "scene_gradual_cuts": using("planted_ramp", sql=_gradual("planted_ramp", "g", 150) + " select * from g"),
    "scene_flash_suppressed": using("frames", sql=_FLASH + "select a.media_id, a.frame_no from f a where a.cut and not exists (select 1 from f b where b.media_id = a.media_id and b.flash and b.frame_no between a.frame_no - 2 and a.frame_no)"),
    "scene_clips": using("frames", sql=f"""c as (select media_id, frame_no, coalesce(abs(luma - {_LAG}) > 150, false) as cut from frames), n as (select *, sum(cast(cut as bigint)) over (partition by media_id order by frame_no) as clip_no from c)
      select media_id, cast(clip_no as bigint) as clip_no, min(frame_no) as start_frame, max(frame_no) as end_frame, count(*) as n_frames from n group by 1, 2 having count(*) >= 3"""),
    "scene_method_agreement": _agreement_sql(),
    "scene_gap_sessions": using("frames", sql="""c as (select media_id, frame_no, texture, coalesce(epoch_us(ts) - lag(epoch_us(ts)) over (partition by media_id order by frame_no) > 7200000000, false) as cut from frames),
      n as (select *, sum(cast(cut as bigint)) over (partition by media_id order by frame_no) as clip_no from c) select media_id, cast(clip_no as bigint) as clip_no, count(*) as n, cast(sum(texture) as bigint) as texture from n group by 1, 2"""),
    "crop_chain": r"""with l as (select doc_id, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) - 1 as k from documents),
      b as (select *, min(case when trim(line) <> '' then k end) over (partition by doc_id) as lo, max(case when trim(line) <> '' then k end) over (partition by doc_id) as hi from l),
      c as (select * from b where k between lo and hi), e as (select *, max(k) over (partition by doc_id) as last_ from c),
      f as (select * from e where not (regexp_matches(lower(line), 'licen|rights reserved') and (k < 2 or k > last_ - 2))),
      g as (select *, sum(length(line) - length(regexp_replace(line, '[*$%&#!|]', '', 'g'))) over (partition by doc_id) as signs, sum(length(line)) over (partition by doc_id) as size from f)
      select doc_id, count(*) as lines, cast(sum(length(line)) as bigint) as chars from g where signs * 100 <= size * 2 group by 1""",
    "crop_dark_border": using("latents88", sql="select item, min(y) filter (abs(val) > 0.15) as y_min, max(y) filter (abs(val) > 0.15) as y_max, min(x) filter (abs(val) > 0.15) as x_min, max(x) filter (abs(val) > 0.15) as x_max from latents88 group by 1"),
    "crop_line_bands": using("text_clips", sql="""l as (select *, max(clip_no) over (partition by doc_id) as last_no from text_clips) select doc_id, count(*) as n, cast(sum(len) as bigint) as chars from l
      where not (regexp_matches(lower(line), 'licen|rights reserved') and (clip_no < 2 or clip_no > last_no - 2)) group by 1"""),
    "page_band_crop": f"select page_id, cast(length({_BAND}) as bigint) as kept_chars from pages",
    "text_share_filter": f"select page_id, visible, total, cast(visible * 10 <= total * 7 as integer) as keep from (select page_id, cast(length({_VIS}) as bigint) as visible, cast(length(html) as bigint) as total from pages)",
    "motion_score": using("frames", sql=_SCORE + "select media_id, n, round(pf + 1e-9, 4) as per_frame, round(ps + 1e-10, 6) as per_second from m"),
    "motion_band_filter": using("frames", sql=_SCORE + ", r as (select media_id, round(pf + 1e-9, 4) as per_frame from m) select media_id, per_frame from r where per_frame between (select quantile_cont(per_frame, 0.05) from r) and (select quantile_cont(per_frame, 0.95) from r)"),
    "motion_block_flow": using("latents", sql="""o as (select cast(i - 1 as bigint) as dy, cast(j - 1 as bigint) as dx from range(3) a(i), range(3) b(j)),
      s as (select a.item, a.t, a.y // 2 as block_y, a.x // 2 as block_x, dy, dx, sum(abs(a.val - b.val)) as sad, count(*) as n from latents a, o, latents b where b.item = a.item and b.t = a.t + 1 and b.y = a.y + dy and b.x = a.x + dx group by 1, 2, 3, 4, 5, 6),
      r as (select *, row_number() over (partition by item, t, block_y, block_x order by round(sad, 9), abs(dy) + abs(dx), dy, dx) as k from s where n = 4) select item, t, block_y, block_x, dy, dx from r where k = 1"""),
}
