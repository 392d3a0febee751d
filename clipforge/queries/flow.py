"""Flow matching, diffusion and latent geometry."""

from __future__ import annotations

from pyspark.sql import functions as F

from clipforge.functions.exprs import key_int, mean_square, rnd, vec_sub, vec_sum
from clipforge.operators import flow as Fl
from clipforge.operators import latent as L
from clipforge.sources import tables as T

from .sqlviews import gauss, h, using

NOISE = gauss("cast(item as varchar) || '_' || cast(i as varchar)")
TIME = "round(1.0 / (1.0 + exp(-" + gauss("cast(item as varchar) || '_t'") + ")), 6)"
_CELLS = f"nz as (select item, label, i, cast(v as double) as x1, {NOISE} as x0, {TIME} as t from cells) "


def pairs(spark, d):
    """Data, keyed noise and a keyed time for each embedding."""
    e = T.load(spark, d, "embeddings")
    return e.select("vec_id", "label", F.transform("embedding", lambda x: x.cast("double")).alias("x1"), Fl.noise_vector(F.col("vec_id"), 64).alias("x0"), Fl.logit_normal_t(F.col("vec_id")).alias("t"))


def checked(df, vec):
    """A vector brought to sums that an oracle can state: of the entries, and of the entries times their place."""
    at = F.aggregate(F.transform(vec, lambda x, i: x * (i + 1)), F.lit(0.0), lambda s, x: s + x)
    return df.select("vec_id", rnd(vec_sum(vec) + 1e-10, 5).alias("total"), rnd(at + 1e-10, 5).alias("placed"))


def loss_by_bin(spark, d):
    p = pairs(spark, d)
    v = Fl.velocity(F.col("x0"), F.col("x1"))
    n = 64
    means = p.select("label", F.posexplode(v).alias("i", "v"))
    glob = means.groupBy("i").agg(F.avg("v").alias("m")).agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "m"))), lambda s: s["m"]).alias("gm"))
    lab = means.groupBy("label", "i").agg(F.avg("v").alias("m")).groupBy("label").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "m"))), lambda s: s["m"]).alias("lm"))
    rows = p.crossJoin(F.broadcast(glob)).join(lab, "label").withColumn("v", v)  # glob is one row of 64 means
    arms = F.array(F.struct(F.lit("zero").alias("predictor"), F.array_repeat(F.lit(0.0), n).alias("u")), F.struct(F.lit("mean").alias("predictor"), F.col("gm").alias("u")),
                   F.struct(F.lit("label_mean").alias("predictor"), F.col("lm").alias("u")), F.struct(F.lit("true").alias("predictor"), F.col("v").alias("u")))
    rows = rows.withColumn("arm", F.explode(arms)).withColumn("t_bin", Fl.t_bin(F.col("t")))
    out = Fl.flow_loss(rows, F.col("arm.u"), F.col("v"), [F.col("arm.predictor").alias("predictor"), F.col("t_bin")])
    return out.select("predictor", "t_bin", "n", rnd(F.col("loss") + 1e-10, 5).alias("loss"))


def euler_steps(spark, d):
    """With the exact velocity any number of steps arrives at the data; with the field's mean it does not."""
    p = pairs(spark, d)
    out = None
    for steps in (4, 8):
        exact = Fl.euler(F.col("x0"), lambda x, t: Fl.velocity(F.col("x0"), F.col("x1")), steps)
        drift = Fl.euler(F.col("x0"), lambda x, t: F.transform(x, lambda e: -e), steps)
        row = p.agg(F.lit(steps).cast("bigint").alias("steps"), rnd(F.avg(mean_square(vec_sub(exact, F.col("x1")))), 8).alias("exact_error"), rnd(F.avg(mean_square(drift)) + 1e-10, 5).alias("decayed_square"))
        out = row if out is None else out.unionByName(row)
    return out


def ddpm(spark, d):
    bars = Fl.ddpm_alpha_bar()
    at = F.array(*[F.lit(round(bars[i], 9)) for i in range(0, 1000, 100)])
    p = pairs(spark, d).withColumn("k", (key_int(F.col("vec_id"), "_d") % 10).cast("int"))
    return checked(p.withColumn("x", Fl.ddpm_noise(F.col("x1"), F.col("x0"), F.get(at, F.col("k")))), F.col("x"))


def guided(spark, d):
    p = pairs(spark, d)
    v = Fl.velocity(F.col("x0"), F.col("x1"))
    return checked(p.withColumn("g", Fl.guide(v, F.transform(F.col("x0"), lambda x: -x), 2.0)), F.col("g"))


def noise_moments(spark, d):
    c = Fl.cell_noise(T.latents(spark, d))
    return c.agg(F.count("*").alias("n"), F.sum(F.col("eps").cast("decimal(12,6)")).cast("double").alias("total"), F.sum((F.col("eps").cast("decimal(12,6)") * F.col("eps").cast("decimal(12,6)")).cast("decimal(20,6)")).cast("double").alias("squares"))


def bars_sql():
    bars = Fl.ddpm_alpha_bar()
    return "[" + ", ".join(f"cast({round(bars[i], 9)} as double)" for i in range(0, 1000, 100)) + "]"


# --- latent geometry -----------------------------------------------------------------------------

def latent_shapes(spark, d):
    f = spark.createDataFrame([(t, 720, 1280) for t in (1, 5, 29, 61, 65, 125)], "t bigint, h bigint, w bigint")
    out = f.select("t", *L.latent_shape(F.col("t"), F.col("h"), F.col("w")))
    return out.withColumn("t_back", L.pixel_shape(F.col("lt"), F.col("lh"), F.col("lw"))[0])


def reconstruction(spark, d):
    f = T.frames(spark, d)
    up = L.upsample(L.causal_pool(f), f)
    return up.groupBy("media_id").agg(rnd(F.avg((F.col("luma") - F.col("latent")) * (F.col("luma") - F.col("latent"))) + 1e-9, 4).alias("mse"))


def tile_blend(spark, d):
    c = L.blend(L.cut_tiles(T.latents(spark, d, "88"), 8, 4, 2))
    return c.select("item", "y", "x", rnd(F.col("blended"), 5).alias("blended"), "cover")


def tile_speedup(spark, d):
    t = L.tiles(spark, (32, 90, 160), (8, 32, 32), (2, 8, 8))
    dev = spark.createDataFrame([(1,), (2,), (4,), (8,)], "devices bigint")
    per = t.crossJoin(F.broadcast(dev)).groupBy("devices", (F.col("tile") % F.col("devices")).alias("device")).agg(F.count("*").alias("n"))  # four rows of device counts
    return per.groupBy("devices").agg(F.sum("n").cast("bigint").alias("tiles"), F.max("n").alias("longest")).withColumn("speedup", rnd(F.col("tiles") / F.col("longest")))


def masks65(spark, d):
    """Masks of 65 frames: on while a keyed phase of the frame is low."""
    e = T.load(spark, d, "embeddings")
    items = e.select(F.col("vec_id").alias("item"))
    return items.withColumn("frame_no", F.explode(F.sequence(F.lit(1).cast("bigint"), F.lit(65).cast("bigint")))).withColumn("m", ((F.col("frame_no") + key_int(F.col("item"), "m")) % 7 < 3).cast("bigint"))


def fold_vs_pool(spark, d):
    m = masks65(spark, d)
    pooled = m.withColumn("g", L.group_of(F.col("frame_no"))).join(L.mask_pool(m), ["item", "g"])
    lost = pooled.agg(F.lit("pool").alias("arm"), F.count_if(F.col("m") != F.col("pooled")).alias("lost_frames"))
    back = L.mask_unfold(L.mask_fold(m)).withColumnRenamed("m", "b").join(m, ["item", "frame_no"])
    return lost.unionByName(back.agg(F.lit("fold").alias("arm"), F.count_if(F.col("m") != F.col("b")).alias("lost_frames")))


QUERIES = {
    "flow_interpolate": lambda s, d: checked(pairs(s, d).withColumn("x", Fl.interpolate(F.col("x0"), F.col("x1"), F.col("t"))), F.col("x")),
    "flow_velocity": lambda s, d: checked(pairs(s, d).withColumn("x", Fl.velocity(F.col("x0"), F.col("x1"))), F.col("x")),
    "flow_time_sample": lambda s, d: pairs(s, d).select("vec_id", "t"),
    "flow_noise_moments": noise_moments, "flow_loss_by_bin": loss_by_bin, "flow_euler_steps": euler_steps, "ddpm_noising": ddpm, "flow_guided": guided,
    "latent_shapes": latent_shapes,
    "causal_pool": lambda s, d: L.causal_pool(T.frames(s, d)).select("media_id", "g", rnd(F.col("latent") + 1e-9, 4).alias("latent"), "n"),
    "pool_reconstruction_mse": reconstruction,
    "tile_cover": lambda s, d: L.cut_tiles(T.latents(s, d, "88").filter("item = 0"), 8, 4, 2).groupBy("y0", "x0").agg(F.count("*").alias("cells"), rnd(F.sum("weight")).alias("weight")),
    "tile_blend": tile_blend, "tile_parallel_speedup": tile_speedup,
    "latent_compression": lambda s, d: s.createDataFrame([(c, float(round(L.compression_ratio(c), 6))) for c in (4, 8, 16, 32)], "channels bigint, ratio double"),
    "patchify_tokens": lambda s, d: L.patchify(T.latents(s, d)).select("item", "t", "py", "px", rnd(F.aggregate(F.transform("patch", lambda v, k: v * (k + 1)), F.lit(0.0), lambda a, x: a + x)).alias("coded")),
    "patchify_round_trip": lambda s, d: L.unpatchify(L.patchify(T.latents(s, d))).groupBy("item").agg(F.count("*").alias("n"), rnd(F.sum(F.col("val") * (F.col("t") * 16 + F.col("y") * 4 + F.col("x") + 1)) + 1e-10, 5).alias("placed")),
    "mask_fold_vs_pool": fold_vs_pool,
}

_VEC = "select item as vec_id, round(sum(x) + 1e-10, 5) + 0.0 as total, round(sum(x * (i + 1)) + 1e-10, 5) + 0.0 as placed from ({}) group by 1"
_TILES = "st(s) as (values (0), (2), (4)), rp(s, c, w) as (select s, c, least(case when s = 0 then 1.0 else least(1.0, (c - s + 1) / 3.0) end, case when s + 4 = 8 then 1.0 else least(1.0, (s + 4 - c) / 3.0) end) from st, range(8) r(c) where s <= c and c < s + 4) "
_MASK = "it as (select vec_id as item from embeddings), mk as (select item, f as frame_no, cast((f + " + h("cast(item as varchar) || 'm'") + ") % 7 < 3 as bigint) as m from it, range(1, 66) r(f)) "
ORACLES = {
    "flow_interpolate": using("cells", sql=_CELLS + _VEC.format("select item, i, (1 - t) * x0 + t * x1 as x from nz")),
    "flow_velocity": using("cells", sql=_CELLS + _VEC.format("select item, i, x1 - x0 as x from nz")),
    "flow_time_sample": f"select item as vec_id, {TIME} as t from (select vec_id as item from embeddings)",
    "flow_noise_moments": using("cells", sql=_CELLS + "select count(*) as n, cast(sum(cast(x0 as decimal(12,6))) as double) as total, cast(sum(cast(cast(x0 as decimal(12,6)) * cast(x0 as decimal(12,6)) as decimal(20,6))) as double) as squares from nz"),
    "flow_loss_by_bin": using("cells", sql=_CELLS + """, v as (select *, x1 - x0 as v, least(cast(floor(t * 4) as bigint), 3) as t_bin from nz), g as (select i, avg(v) as m from v group by 1), l as (select label, i, avg(v) as m from v group by 1, 2),
      a as (select 'zero' as predictor, item, t_bin, v * v as e from v union all select 'mean', item, t_bin, (v - m) * (v - m) from v join g using (i) union all select 'label_mean', item, t_bin, (v - m) * (v - m) from v join l using (label, i) union all select 'true', item, t_bin, 0.0 from v)
      select predictor, t_bin, count(distinct item) as n, round(avg(e) + 1e-10, 5) as loss from a group by 1, 2"""),
    "flow_euler_steps": using("cells", sql=_CELLS + "select cast(s as bigint) as steps, cast(0.0 as double) as exact_error, round(avg(x0 * x0) * pow(pow(1 - 1.0 / s, s), 2) + 1e-10, 5) as decayed_square from nz, (values (4), (8)) v(s) group by s"),
    "ddpm_noising": using("cells", sql=_CELLS + f", q as (select *, {bars_sql()}[" + h("cast(item as varchar) || '_d'") + " % 10 + 1] as ab from nz) " + _VEC.format("select item, i, sqrt(ab) * x1 + sqrt(1.0 - ab) * x0 as x from q")),
    "flow_guided": using("cells", sql=_CELLS + _VEC.format("select item, i, (x1 - x0) + 2.0 * ((x1 - x0) + x0) as x from nz")),
    "latent_shapes": "select cast(t as bigint) as t, cast(1 + (t - 1) // 4 as bigint) as lt, cast(90 as bigint) as lh, cast(160 as bigint) as lw, cast(((t - 1) // 4) * 4 + 1 as bigint) as t_back from (values (1), (5), (29), (61), (65), (125)) v(t)",
    "causal_pool": using("frames", sql="select media_id, cast(ceil((frame_no - 1) / 4) as bigint) as g, round(avg(luma) + 1e-9, 4) as latent, count(*) as n from frames group by 1, 2"),
    "pool_reconstruction_mse": using("frames", sql="f as (select media_id, luma, avg(luma) over (partition by media_id, cast(ceil((frame_no - 1) / 4) as bigint)) as l from frames) select media_id, round(avg((luma - l) * (luma - l)) + 1e-9, 4) as mse from f group by 1"),
    "tile_cover": f"with {_TILES} select cast(a.s as bigint) as y0, cast(b.s as bigint) as x0, count(*) as cells, round(sum(a.w * b.w), 6) as weight from rp a, rp b group by 1, 2",
    "tile_blend": using("latents88", sql="select item, y, x, round(val, 5) + 0.0 as blended, cast((case when y between 2 and 5 then 2 else 1 end) * (case when x between 2 and 5 then 2 else 1 end) as bigint) as cover from latents88"),
    "tile_parallel_speedup": "with n as (select 5 * 4 * 7 - 5 * 4 * 7 + (select count(*) from (values (0), (6), (12), (18), (24)) t(a), (values (0), (24), (48), (58)) y(b), (values (0), (24), (48), (72), (96), (120), (128)) x(c)) as k) select cast(v as bigint) as devices, cast(k as bigint) as tiles, cast(ceil(k / v) as bigint) as longest, round(k / ceil(k / v), 6) as speedup from n, (values (1), (2), (4), (8)) d(v)",
    "latent_compression": "select cast(c as bigint) as channels, round(768.0 / c, 6) as ratio from (values (4), (8), (16), (32)) v(c)",
    "patchify_tokens": using("latents", sql="select item, t, y // 2 as py, x // 2 as px, round(sum(val * ((y % 2) * 2 + x % 2 + 1)), 6) + 0.0 as coded from latents group by 1, 2, 3, 4"),
    "patchify_round_trip": using("latents", sql="select item, count(*) as n, round(sum(val * (i + 1)) + 1e-10, 5) + 0.0 as placed from latents group by 1"),
    "mask_fold_vs_pool": f"with {_MASK}, g as (select *, round(avg(m) over (partition by item, cast(ceil((frame_no - 1) / 4) as bigint))) as p from mk) select 'pool' as arm, count(*) filter (m <> p) as lost_frames from g union all select 'fold', 0",
}
