"""Window fusion, masks, fillers, the completion scoreboard and metrics."""

from __future__ import annotations

from pyspark.sql import functions as F

from clipforge.functions.exprs import int_div, key_int, rnd
from clipforge.operators import fusion as Fu
from clipforge.operators import metrics as M
from clipforge.sources import tables as T
from clipforge.sources.scratch import materialize

from .sqlviews import gauss, h, using

N, S, PEAK, SET = 17, 8, 500.0, 50


def track(s, d):
    return T.frames(s, d).select(F.col("media_id").alias("item"), (F.col("frame_no") - 1).alias("i"), F.col("luma").alias("val"))


def masked(s, d):
    return Fu.track_mask(track(s, d))


def out(df):
    return df.select("item", "i", rnd(F.col("val") + 1e-9, 4).alias("val"))


def windows(s, d):
    t = s.createDataFrame([(k, n) for k, n in enumerate((1, 17, 25, 33, 40, 65))], "item bigint, total bigint")
    a = Fu.fusion_windows(t, 17, 8).withColumn("stride", F.lit(8).cast("bigint"))
    return a.unionByName(Fu.fusion_windows(t, 17, 17).withColumn("stride", F.lit(17).cast("bigint")))


def coverage(s, d):
    return Fu.members(track(s, d), N, S).groupBy("item", "i").agg(F.count("*").alias("cover"))


def seams(s, d):
    f = Fu.seam_jump(Fu.fused_denoise(track(s, d), 4, N, S), N).withColumn("arm", F.lit("fused"))
    return f.unionByName(Fu.seam_jump(Fu.concat_clips(track(s, d), 4, N), N).withColumn("arm", F.lit("concat"))).select("arm", "seams", rnd(F.col("jump") + 1e-9, 4).alias("jump"))


def filled(df):
    return df.filter("m = 1").groupBy("item").agg(F.count("*").alias("n"), rnd(F.sum("filled") + 1e-9, 4).alias("total"))


def videos(s, d, hidden, n=None):
    """Pictures of 4 x 4 pixels: a track's brightness over a keyed texture that drifts; the test set is a keyed sample of ``n`` tracks."""
    f = T.frames(s, d)
    if n:
        f = f.join(F.broadcast(f.select("media_id").distinct().orderBy(key_int(F.col("media_id"), "set"), "media_id").limit(n)), "media_id")
    rows = f.select(F.col("media_id").alias("item"), (F.col("frame_no") - 1).alias("i"), "luma")
    side = F.sequence(F.lit(0).cast("bigint"), F.lit(3).cast("bigint"))
    rows = rows.withColumn("y", F.explode(side)).withColumn("x", F.explode(side))
    texture = (key_int(F.col("item"), "_", (F.col("x") + int_div(F.col("i"), 8)) % 4, "_", F.col("y")) % 41 - 20).cast("double")
    rows = rows.withColumn("val", F.col("luma") * 0.25 + texture)
    return (Fu.moving_mask(rows.withColumn("t", F.col("i"))).drop("t") if hidden == "moving" else Fu.stationary_mask(rows, 2, 4)).select("item", "i", "y", "x", "val", "m")


def video_latents(s, d):
    c = Fu.condition_latents(Fu.encode_masked(videos(s, d, "moving", SET), 4))
    return c.select("item", "c", "i", rnd(F.col("ctx") + 1e-9, 4).alias("ctx"), rnd(F.col("seen")).alias("seen"))


def video_tokens(s, d):
    t = Fu.token_inputs(Fu.condition_latents(Fu.encode_masked(videos(s, d, "moving", SET), 4)))
    return t.groupBy("item").agg(F.count("*").alias("tokens"), rnd(F.sum(F.aggregate(F.transform("token", lambda v, k: v * (k + 1)), F.lit(0.0), lambda a, x: a + x)) + 1e-9, 4).alias("placed"))


def flow_filled(steps):
    def run(s, d):
        v = Fu.inpaint(videos(s, d, "moving", SET), steps)
        return v.filter("m = 1").groupBy("item").agg(F.count("*").alias("n"), rnd(F.sum("filled") + 1e-9, 4).alias("total"))

    return run


ARMS = {"flow_4": lambda v: Fu.inpaint(v, 4), "flow_8": lambda v: Fu.inpaint(v, 8), "propagate": lambda v: Fu.fill_pixels(v, Fu.fill_propagate), "linear": lambda v: Fu.fill_pixels(v, Fu.fill_linear), "mean": lambda v: Fu.fill_pixels(v, Fu.fill_mean)}


def scoreboard(s, d):
    """Fifty videos under moving and stationary masks, completed by each arm, reduced in size, then scored."""
    pixels = None
    for hidden in ("moving", "stationary"):
        v = materialize(videos(s, d, hidden, SET), "videos")
        for name, arm in ARMS.items():
            part = arm(v).select(F.lit(f"{hidden}/{name}").alias("arm"), "item", "i", "y", "x", F.col("val").alias("a"), F.col("filled").alias("b"))
            pixels = part if pixels is None else pixels.unionByName(part)
    rows = materialize(M.resize_pairs(pixels), "scored")  # every arm is computed once
    c = M.compare(rows, PEAK, F.col("y") * 2 + F.col("x"))
    return c.select("arm", rnd(F.col("psnr") + 1e-10, 4).alias("psnr"), rnd(F.col("ssim") + 1e-10, 5).alias("ssim"), rnd(F.col("frechet") + 1e-8, 3).alias("frechet"))


def decaption(s, d):
    """A caption band over the bottom rows of every frame, removed by each arm: what is left of the difference, and flicker."""
    v = videos(s, d, "moving", SET).withColumn("m", (F.col("y") == 3).cast("bigint"))
    out = None
    for name, arm in (("flow_4", ARMS["flow_4"]), ("flow_8", ARMS["flow_8"]), ("mean", ARMS["mean"])):
        done = materialize(arm(v).select("item", "i", "y", "x", F.col("val").alias("a"), F.col("filled").alias("b")), "decaption")
        p = M.psnr(done, PEAK, ("item", "i"))
        band = done.filter("y = 3").groupBy("item", "i").agg(F.avg("a").alias("a"), F.avg("b").alias("b"))
        row = p.crossJoin(M.flicker(band)).select(F.lit(name).alias("arm"), rnd(F.col("psnr") + 1e-10, 4).alias("psnr"), rnd(F.col("flicker") + 1e-9, 4).alias("flicker"))
        out = row if out is None else out.unionByName(row)
    return out


def pairs88(s, d):
    """Two versions of a frame: as it is, and with its band replaced by the mean of the rest."""
    from pyspark.sql import Window as W

    c = Fu.band_mask(T.latents(s, d, "88"))
    mean = F.avg(F.when(F.col("m") == 0, F.col("val"))).over(W.partitionBy("item"))
    return c.select("item", F.lit(0).alias("frame"), F.col("i").alias("feature"), "y", "x", "i", F.col("val").alias("a"), F.when(F.col("m") == 0, F.col("val")).otherwise(mean).alias("b"))


def frechet_full(s, d):
    """Full covariance on all 64 features: a matrix root, so no oracle."""
    e = T.load(s, d, "embeddings")
    v = M.frechet(e.filter("vec_id % 2 = 0"), e.filter("vec_id % 2 = 1"), "embedding", 64)
    return s.createDataFrame([(round(v, 6),)], "frechet double")


QUERIES = {
    "fusion_windows": windows, "fusion_coverage": coverage,
    "fusion_average": lambda s, d: out(Fu.fuse(Fu.smooth(Fu.members(track(s, d), N, S)))),
    "fusion_denoise": lambda s, d: out(Fu.fused_denoise(track(s, d), 2, N, S)),
    "fusion_denoise_grouped": lambda s, d: out(Fu.fused_denoise_grouped(track(s, d), 2, N, S)),
    "fusion_vs_concat_seam": seams,
    "inpaint_latents": video_latents, "inpaint_token_sums": video_tokens, "inpaint_flow": flow_filled(4), "inpaint_flow_8": flow_filled(8), "inpaint_decaption": decaption,
    "inpaint_tokens": lambda s, d: s.createDataFrame([(30, 54, 17), (90, 160, 17)], "h bigint, w bigint, n bigint").select("h", "w", Fu.inpaint_tokens(F.col("w"), F.col("h"), F.col("n")).alias("summed"), (Fu.inpaint_tokens(F.col("w"), F.col("h"), F.col("n")) * 3).alias("concatenated")),
    "mask_stationary": lambda s, d: Fu.stationary_mask(T.latents(s, d, "88")).groupBy("item").agg(F.sum("m").cast("bigint").alias("cells"), F.sum(F.col("m") * F.col("i")).cast("bigint").alias("places")),
    "mask_moving": lambda s, d: Fu.moving_mask(T.latents(s, d)).groupBy("item", "t").agg(F.sum("m").cast("bigint").alias("cells"), F.sum(F.col("m") * F.col("i")).cast("bigint").alias("places")),
    "mask_band": lambda s, d: Fu.band_mask(T.latents(s, d, "88")).groupBy("item").agg(F.sum("m").cast("bigint").alias("cells"), rnd(F.sum(F.col("m") * F.col("val")) + 1e-10).alias("hidden")),
    "inpaint_propagate": lambda s, d: filled(Fu.fill_propagate(masked(s, d))), "inpaint_linear": lambda s, d: filled(Fu.fill_linear(masked(s, d))), "inpaint_mean": lambda s, d: filled(Fu.fill_mean(masked(s, d))),
    "inpaint_stage_plan": lambda s, d: s.createDataFrame([("coarse", 240, 500_000, 16, 65), ("fine", 720, 200_000, 16, 65)], "stage string, res bigint, steps bigint, batch bigint, frames bigint").withColumn("samples", F.col("steps") * F.col("batch")),
    "inpaint_scoreboard": scoreboard,
    "metric_psnr": lambda s, d: M.psnr(pairs88(s, d), 1.0).select(rnd(F.col("psnr") + 1e-10, 5).alias("psnr")),
    "metric_ssim": lambda s, d: M.ssim(pairs88(s, d), 1.0).withColumn("kind", F.lit("frame")).unionByName(M.ssim(pairs88(s, d).withColumn("wy", int_div(F.col("y"), 4)).withColumn("wx", int_div(F.col("x"), 4)), 1.0, per=("item", "wy", "wx")).withColumn("kind", F.lit("window"))).select("kind", rnd(F.col("ssim") + 1e-10, 5).alias("ssim")),
    "metric_frechet_diag": lambda s, d: M.frechet_diag(pairs88(s, d)).select(rnd(F.col("frechet") + 1e-10, 5).alias("frechet")),
    "metric_frechet_full": frechet_full,
    "metric_resize": lambda s, d: M.resize_area(T.latents(s, d, "88"), 8, 4).select("item", "y", "x", rnd(F.col("val") + 1e-10).alias("val")),
    "metric_flicker": lambda s, d: M.flicker(Fu.fused_denoise(track(s, d), 1, N, S).withColumnRenamed("val", "b").join(track(s, d).withColumnRenamed("val", "a"), ["item", "i"])).select(rnd(F.col("flicker") + 1e-9, 4).alias("flicker")),
}

_TRK = "tr as (select media_id as item, frame_no - 1 as i, luma as val, count(*) over (partition by media_id) as total from frames)"


def _win(n, s, total="total"):
    return f"case when {total} <= {n} then [0] else list_distinct(list_transform(range(cast(ceil(({total} - {n}) / {s}) as bigint) + 1), lambda k: least(k * {s}, {total} - {n}))) end"


def _steps(src, steps, prefix="d"):
    ctes, prev = [], src
    for k in range(steps):
        mm, sm, nx = f"{prefix}m{k}", f"{prefix}s{k}", f"{prefix}{k + 1}"
        ctes += [f"{mm} as (select item, i, val, total, st from (select *, unnest({_win(N, S)}) as st from {prev}) where st <= i and i < st + {N})",
                 f"{sm} as (select item, i, total, 0.5 * val + 0.5 * avg(val) over (partition by item, st order by i rows between 1 preceding and 1 following) as val from {mm})",
                 f"{nx} as (select item, i, any_value(total) as total, avg(val) as val from {sm} group by 1, 2)"]
        prev = nx
    return ", ".join(ctes)


_MK = "mk as (select *, cast((i + " + h("cast(item as varchar) || 'tm'") + ") % 16 < 5 as bigint) as m from tr)"
_KN = f"""{_MK}, kn as (select *, last_value(case when m = 0 then val end ignore nulls) over b as va, last_value(case when m = 0 then i end ignore nulls) over b as ia, first_value(case when m = 0 then val end ignore nulls) over f as vb, first_value(case when m = 0 then i end ignore nulls) over f as ib
  from mk window b as (partition by item order by i rows between unbounded preceding and current row), f as (partition by item order by i rows between current row and unbounded following))"""
_LIN = "case when m = 0 then val else coalesce(case when va is null then vb when vb is null then va else va + (vb - va) * (i - ia) / greatest(ib - ia, 1) end, 0.0) end"
_PRO = "case when m = 0 then val else coalesce(case when va is null then vb when vb is null then va when i - ia <= ib - i then va else vb end, 0.0) end"
_MEAN = "case when m = 0 then val else coalesce(avg(case when m = 0 then val end) over (partition by item), 0.0) end"
_FILL = "select item, count(*) as n, round(sum(filled) + 1e-9, 4) + 0.0 as total from {} where m = 1 group by 1"


def _move(k):
    p = "(" + h(f"cast(item as varchar) || '{k}'") + " + t * (" + h(f"cast(item as varchar) || '{k}v'") + " % 2 + 1)) % 4"
    return f"case when {p} <= 2 then {p} else 4 - {p} end"


def _videos(hidden, name="vd"):
    if hidden == "moving":
        mask = f"y between {_move('my')} and {_move('my')} + 1 and x between {_move('mx')} and {_move('mx')} + 1"
    elif hidden == "stationary":
        y0, x0 = (h(f"cast(item as varchar) || '{k}'") + " % 3" for k in ("my", "mx"))
        mask = f"y between {y0} and {y0} + 1 and x between {x0} and {x0} + 1"
    else:
        mask = "y = 3"
    texture = h("cast(item as varchar) || '_' || cast((x + t // 8) % 4 as varchar) || '_' || cast(y as varchar)") + " % 41 - 20"
    return f"""{name} as (select item, t as i, y, x, luma * 0.25 + ({texture}) as val, cast({mask} as bigint) as m
      from (select media_id as item, frame_no - 1 as t, luma from frames where media_id in (select media_id from (select distinct media_id from frames) order by {h("cast(media_id as varchar) || 'set'")}, media_id limit 50)), range(4) a(y), range(4) b(x))"""


def _conditioned(src, p):
    eps = gauss("cast(item as varchar) || '_' || cast(g as varchar) || '_' || cast(c as varchar)")
    k_ = lambda k: f"coalesce(avg(case when (i + 3) % 4 = {k} or i = 0 then m end), 1.0)"
    return f"""{p}n as (select item, cast(ceil(i / 4) as bigint) as g, (y // 2) * 2 + x // 2 as c, avg(case when m = 0 then val end) as y1, 1 - ({k_(0)} + {k_(1)} + {k_(2)} + {k_(3)}) / 4 as seen from {src} group by 1, 2, 3),
      {p}k as (select *, last_value(y1 ignore nulls) over b as va, last_value(case when y1 is not null then g end ignore nulls) over b as ga, first_value(y1 ignore nulls) over f as vb, first_value(case when y1 is not null then g end ignore nulls) over f as gb
        from {p}n window b as (partition by item, c order by g rows between unbounded preceding and current row), f as (partition by item, c order by g rows between current row and unbounded following)),
      {p}l as (select *, case when va is null then vb when vb is null then va else va + (vb - va) * (g - ga) / greatest(gb - ga, 1) end as line from {p}k),
      {p}c as (select item, c, g as i, coalesce(line, avg(line) over (partition by item, g), 0.0) as ctx, seen, {eps} as eps, count(*) over (partition by item, c) as total from {p}l)"""


def _flow(p, steps):
    ctes, prev = [f"{p}{steps}x0 as (select *, eps as val from {p}c)"], f"{p}{steps}x0"
    starts = "case when total <= 8 then [0] else list_distinct(list_transform(range(cast(ceil((total - 8) / 4) as bigint) + 1), lambda k: least(k * 4, total - 8))) end"
    for k in range(steps):
        m, v, nx = (f"{p}{steps}{c}{k + 1}" for c in "mvx")
        t = k / steps
        ctes += [f"{m} as (select * from (select *, unnest({starts}) as st from {prev}) where st <= i and i < st + 8)",
                 f"{v} as (select item, c, i, ctx, seen, eps, total, val + ((0.5 + 0.5 * seen) * ctx + (1 - (0.5 + 0.5 * seen)) * avg(val + (1 - cast({t} as double)) * (ctx - eps)) over (partition by item, c, st order by i rows between 1 preceding and 1 following) - eps) / {steps} as val from {m})",
                 f"{nx} as (select item, c, i, any_value(ctx) as ctx, any_value(seen) as seen, any_value(eps) as eps, any_value(total) as total, avg(val) as val from {v} group by 1, 2, 3)"]
        prev = nx
    return ", ".join(ctes), prev


def _made(src, final):
    return f"select v.item, v.i, v.y, v.x, v.m, v.val as a, case when v.m = 0 then v.val else e.val end as b from {src} v join {final} e on e.item = v.item and e.i = cast(ceil(v.i / 4) as bigint) and e.c = (v.y // 2) * 2 + v.x // 2"


def _known(src, name):
    return f"""{name} as (select *, min(m) over (partition by item, y, x) as never, avg(case when m = 0 then val end) over (partition by item, i) as beside, avg(case when m = 0 then val end) over (partition by item, y, x) as own,
      last_value(case when m = 0 then val end ignore nulls) over b as va, last_value(case when m = 0 then i end ignore nulls) over b as ia, first_value(case when m = 0 then val end ignore nulls) over f as vb, first_value(case when m = 0 then i end ignore nulls) over f as ib
      from {src} window b as (partition by item, y, x order by i rows between unbounded preceding and current row), f as (partition by item, y, x order by i rows between current row and unbounded following))"""


def _filled(known, expr):
    return f"select item, i, y, x, m, val as a, case when never = 1 then coalesce(beside, 0.0) else {expr} end as b from {known}"


_PIXEL = {"propagate": _PRO, "linear": _LIN, "mean": "case when m = 0 then val else coalesce(own, 0.0) end"}


def _scores_sql():
    ctes, arms = [], {}
    for hidden, p in (("moving", "mo"), ("stationary", "sn")):
        ctes += [_videos(hidden, f"{p}v"), _conditioned(f"{p}v", p), _known(f"{p}v", f"{p}kn")]
        for steps in (4, 8):
            part, final = _flow(p, steps)
            ctes.append(part)
            arms[f"{hidden}/flow_{steps}"] = _made(f"{p}v", final)
        arms |= {f"{hidden}/{k}": _filled(f"{p}kn", e) for k, e in _PIXEL.items()}
    union = " union all ".join(f"select '{k}' as arm, item, i, y // 2 as y, x // 2 as x, avg(a) as a, avg(b) as b from ({v}) group by all" for k, v in arms.items())
    return using("frames", sql=f"""{', '.join(ctes)}, al as ({union}),
      ps as (select arm, item, i, avg((a - b) * (a - b)) as mse, avg(a) as ma, avg(b) as mb, var_pop(a) as va, var_pop(b) as vb, covar_pop(a, b) as cov from al group by 1, 2, 3),
      p as (select arm, avg(case when mse > 0 then least(100.0, 10 * log10(250000.0 / mse)) else 100.0 end) as psnr, avg((2 * ma * mb + 25.0) * (2 * cov + 225.0) / ((ma * ma + mb * mb + 25.0) * (va + vb + 225.0))) as ssim from ps group by 1),
      fr as (select arm, y, x, avg(a) as ma, avg(b) as mb, var_pop(a) as va, var_pop(b) as vb from al group by 1, 2, 3), f as (select arm, sum((ma - mb) * (ma - mb) + va + vb - 2 * sqrt(va * vb)) as frechet from fr group by 1)
      select arm, round(psnr + 1e-10, 4) as psnr, round(ssim + 1e-10, 5) as ssim, round(frechet + 1e-8, 3) as frechet from p join f using (arm)""")


def _decaption_sql():
    flows = [_flow("dc", n) for n in (4, 8)]
    arms = {"flow_4": _made("dcv", flows[0][1]), "flow_8": _made("dcv", flows[1][1]), "mean": _filled("dckn", _PIXEL["mean"])}
    union = " union all ".join(f"select '{k}' as arm, item, i, y, a, b from ({v})" for k, v in arms.items())
    return using("frames", sql=f"""{_videos('band', 'dcv')}, {_conditioned('dcv', 'dc')}, {_known('dcv', 'dckn')}, {flows[0][0]}, {flows[1][0]}, al as ({union}),
      ps as (select arm, item, i, avg((a - b) * (a - b)) as mse from al group by 1, 2, 3), p as (select arm, avg(case when mse > 0 then least(100.0, 10 * log10(250000.0 / mse)) else 100.0 end) as psnr from ps group by 1),
      bd as (select arm, item, i, avg(a) as a, avg(b) as b from al where y = 3 group by 1, 2, 3), st as (select arm, abs(a - lag(a) over w) as sa, abs(b - lag(b) over w) as sb from bd window w as (partition by arm, item order by i)), fl as (select arm, avg(sb) - avg(sa) as flicker from st group by 1)
      select arm, round(psnr + 1e-10, 4) as psnr, round(flicker + 1e-9, 4) + 0.0 as flicker from p join fl using (arm)""")


def _flow_filled(steps):
    part, final = _flow("mo", steps)
    return using("frames", sql=f"{_videos('moving', 'mov')}, {_conditioned('mov', 'mo')}, {part}, al as ({_made('mov', final)}) select item, count(*) as n, round(sum(b) + 1e-9, 4) + 0.0 as total from al where m = 1 group by 1")


_P88 = "pb as (select item, i, y, x, val as a, case when y < 6 then val else avg(case when y < 6 then val end) over (partition by item) end as b from latents88)"
_SS = "avg((2 * ma * mb + 0.0001) * (2 * cov + 0.0009) / ((ma * ma + mb * mb + 0.0001) * (va + vb + 0.0009)))"
_AG = "avg(a) as ma, avg(b) as mb, var_pop(a) as va, var_pop(b) as vb, covar_pop(a, b) as cov"


ORACLES = {
    "fusion_windows": "with t(item, total) as (values (0, 1), (1, 17), (2, 25), (3, 33), (4, 40), (5, 65)), s(stride) as (values (8), (17)), c as (select *, case when total <= 17 then 1 else cast(ceil((total - 17) / stride) as bigint) + 1 end as n from t, s) select cast(item as bigint) as item, cast(k as bigint) as clip, cast(greatest(0, least(k * stride, total - 17)) as bigint) as start, cast(least(17, total) as bigint) as size, cast(stride as bigint) as stride from c, range(9) r(k) where k < n",
    "fusion_coverage": using("frames", sql=f"{_TRK}, w as (select item, total, unnest({_win(N, S)}) as st from (select distinct item, total from tr)) select tr.item, tr.i, count(*) as cover from tr join w on w.item = tr.item and st <= i and i < st + {N} group by 1, 2"),
    "fusion_average": using("frames", sql=f"{_TRK}, {_steps('tr', 1)} select item, i, round(val + 1e-9, 4) + 0.0 as val from d1"),
    "fusion_denoise": using("frames", sql=f"{_TRK}, {_steps('tr', 2)} select item, i, round(val + 1e-9, 4) + 0.0 as val from d2"),
    "fusion_denoise_grouped": using("frames", sql=f"{_TRK}, {_steps('tr', 2)} select item, i, round(val + 1e-9, 4) + 0.0 as val from d2"),
    "fusion_vs_concat_seam": using("frames", sql=f"{_TRK}, {_steps('tr', 4)}, c0 as (select item, i, val from tr), " + ", ".join(f"c{k + 1} as (select item, i, 0.5 * val + 0.5 * avg(val) over (partition by item, i // 17 order by i rows between 1 preceding and 1 following) as val from c{k})" for k in range(4)) +
        ", j as (select 'fused' as arm, i, abs(val - lag(val) over (partition by item order by i)) as s from d4 union all select 'concat', i, abs(val - lag(val) over (partition by item order by i)) from c4) select arm, count(*) as seams, round(avg(s) + 1e-9, 4) as jump from j where i % 17 = 0 and i > 0 group by 1"),
    "inpaint_latents": using("frames", sql=f"{_videos('moving', 'mov')}, {_conditioned('mov', 'mo')} select item, c, i, round(ctx + 1e-9, 4) + 0.0 as ctx, round(seen, 6) as seen from moc"),
    "inpaint_token_sums": using("frames", sql=f"{_videos('moving', 'mov')}, {_conditioned('mov', 'mo')} select item, count(distinct i) as tokens, round(sum((ctx + seen + eps) * (c + 1)) + 1e-9, 4) + 0.0 as placed from moc group by 1"),
    "inpaint_flow": _flow_filled(4), "inpaint_flow_8": _flow_filled(8), "inpaint_decaption": _decaption_sql(),
    "inpaint_tokens": "select cast(h as bigint) as h, cast(w as bigint) as w, cast(h * w * 17 // 4 as bigint) as summed, cast(h * w * 17 // 4 * 3 as bigint) as concatenated from (values (30, 54), (90, 160)) v(h, w)",
    "mask_stationary": using("latents88", sql="q as (select item, i, y, x, " + h("cast(item as varchar) || 'my'") + " % 6 as y0, " + h("cast(item as varchar) || 'mx'") + " % 6 as x0 from latents88) select item, count(*) filter (y between y0 and y0 + 2 and x between x0 and x0 + 2) as cells, cast(sum(case when y between y0 and y0 + 2 and x between x0 and x0 + 2 then i else 0 end) as bigint) as places from q group by 1"),
    "mask_moving": using("latents", sql=f"q as (select item, i, t, y, x, {_move('my')} as y0, {_move('mx')} as x0 from latents) select item, t, count(*) filter (y between y0 and y0 + 1 and x between x0 and x0 + 1) as cells, cast(sum(case when y between y0 and y0 + 1 and x between x0 and x0 + 1 then i else 0 end) as bigint) as places from q group by 1, 2"),
    "mask_band": using("latents88", sql="select item, count(*) filter (y >= 6) as cells, round(sum(case when y >= 6 then val else 0 end) + 1e-10, 6) + 0.0 as hidden from latents88 group by 1"),
    **{f"inpaint_{n}": using("frames", sql=f"{_TRK}, {_KN}, fl as (select item, m, {e} as filled from kn) " + _FILL.format("fl")) for n, e in (("propagate", _PRO), ("linear", _LIN), ("mean", _MEAN))},
    "inpaint_stage_plan": "select a as stage, cast(b as bigint) as res, cast(c as bigint) as steps, cast(16 as bigint) as batch, cast(65 as bigint) as frames, cast(c * 16 as bigint) as samples from (values ('coarse', 240, 500000), ('fine', 720, 200000)) v(a, b, c)",
    "inpaint_scoreboard": _scores_sql(),
    "metric_psnr": using("latents88", sql=f"{_P88}, m as (select item, avg((a - b) * (a - b)) as mse from pb group by 1) select round(avg(case when mse > 0 then least(100.0, 10 * log10(1.0 / mse)) else 100.0 end) + 1e-10, 5) as psnr from m"),
    "metric_ssim": using("latents88", sql=f"{_P88}, f as (select item, {_AG} from pb group by 1), w as (select item, y // 4 as wy, x // 4 as wx, {_AG} from pb group by 1, 2, 3) select 'frame' as kind, round({_SS} + 1e-10, 5) as ssim from f union all select 'window', round({_SS} + 1e-10, 5) from w"),
    "metric_frechet_diag": using("latents88", sql=f"{_P88}, f as (select i, avg(a) as ma, avg(b) as mb, var_pop(a) as va, var_pop(b) as vb from pb group by 1) select round(sum((ma - mb) * (ma - mb) + va + vb - 2 * sqrt(va * vb)) + 1e-10, 5) as frechet from f"),
    "metric_resize": using("latents88", sql="select item, y // 2 as y, x // 2 as x, round(avg(val) + 1e-10, 6) + 0.0 as val from latents88 group by 1, 2, 3"),
    "metric_flicker": using("frames", sql=f"{_TRK}, {_steps('tr', 1)}, s as (select abs(d1.val - lag(d1.val) over w) as sb, abs(tr.val - lag(tr.val) over w) as sa from tr join d1 using (item, i) window w as (partition by tr.item order by tr.i)) select round(avg(sb) - avg(sa) + 1e-9, 4) as flicker from s"),
}
