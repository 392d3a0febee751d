"""Buckets, batches, stages and mixing."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import int_div, key_int, rnd
from clipforge.operators import buckets as B
from clipforge.operators import curriculum as C
from clipforge.sources import tables as T

from .sqlviews import h, using

BUDGET = 51_200
# The five published buckets, written out for the oracles, with the latent cells of a batch: 51,200, 50,880, 50,880, 51,200 and 102,400.
LITERAL = """buckets(bucket_id, batch, t, h, w) as (select cast(a as bigint), cast(b as bigint), cast(c as bigint), cast(d as bigint), cast(e as bigint)
  from (values (0, 1, 29, 640, 640), (1, 1, 29, 480, 854), (2, 1, 29, 854, 480), (3, 1, 125, 320, 320), (4, 8, 29, 320, 320)) v(a, b, c, d, e))"""
STAGE_LIT = "stages(stage, step_no, image_res, s_frames, video_res, batch, steps, lr) as (values {})".format(", ".join(f"('{s[0]}', " + ", ".join(f"cast({x} as bigint)" for x in s[1:7]) + f", cast({s[7]} as double))" for s in C.STAGES))
CELLS = "(1 + (t - 1) // 4) * (h // 8) * (w // 8)"
LENGTHS = sorted({b[1] for b in B.PRINTED})
FLOOR = using("media_meta", sql=f"""{LITERAL}, f as (select *, (select max(t) from buckets where t <= frames) as bucket_t from media_meta),
  a as (select f.*, b.bucket_id, b.batch, b.t, b.h, b.w, row_number() over (partition by media_id order by abs(b.h * b.w - height * width), abs(width * b.h - height * b.w), b.bucket_id) as k from f join buckets b on b.t = f.bucket_t) """)
STAGE_RES = ((61, 320), (61, 640), (125, 640), (125, 960))


def assigned(spark, d):
    return B.assign_bucket(T.media_meta(spark, d)).filter("bucket is not null").select("media_id", "frames", "height", "width", "bucket_t", F.col("bucket.id").alias("bucket_id"), F.col("bucket.b").alias("batch"), F.col("bucket.t").alias("t"), F.col("bucket.h").alias("h"), F.col("bucket.w").alias("w"))


def bucket_assign(spark, d):
    """Gate, assignment, counts per bucket."""
    from clipforge.operators.container import metadata_gate

    kept = metadata_gate(T.media_meta(spark, d)).filter(F.size("reasons") == 0)
    return B.assign_bucket(kept).groupBy(F.coalesce(F.col("bucket.id"), F.lit(-1).cast("bigint")).alias("bucket_id")).agg(F.count("*").alias("n"), F.sum("frames").cast("bigint").alias("frames"))


def bucket_media(spark, d):
    """The published buckets with the number of media assigned to each; a bucket without media stays."""
    n = assigned(spark, d).groupBy("bucket_id").agg(F.count("*").alias("media"))
    table = B.with_tokens(B.bucket_table(spark, B.PRINTED))
    return table.join(F.broadcast(n), "bucket_id", "left").withColumn("media", F.coalesce("media", F.lit(0).cast("bigint")))  # n is a row a bucket


def bucket_token_spread(spark, d):
    """Cells of a batch over the media that were assigned: least, most, and one by the other."""
    a = assigned(spark, d).withColumn("cells", F.col("batch") * B.latent_cells(F.col("t"), F.col("h"), F.col("w")))
    return a.agg(F.count("*").alias("media"), F.min("cells").alias("least"), F.max("cells").alias("most"), rnd(F.max("cells") / F.min("cells")).alias("spread"))


def bucket_tune_batch(spark, d):
    """The greatest batch within the budget, and how many such batches the bucket's media fill."""
    tuned = B.tune_batch(bucket_media(spark, d), BUDGET)
    return tuned.select("bucket_id", "tuned", "media", F.ceil(F.col("media") / F.col("tuned")).cast("bigint").alias("batches"))


def by_rule(rule):
    return lambda s, d: B.assign_frames(T.media_meta(s, d), LENGTHS, rule).groupBy(F.coalesce("bucket_t", F.lit(0).cast("bigint")).alias("bucket_t")).agg(F.count("*").alias("n"), F.sum("frames").cast("bigint").alias("frames"))


def batches(spark, d):
    return B.pack_batches(assigned(spark, d))


def bucket_step_balance(spark, d):
    """Steps of eight batches in keyed order: waiting of bucketed batches."""
    b = batches(spark, d).groupBy("bucket_id", "shard", "batch_no").agg(F.count("*").alias("n"), F.first(B.latent_cells(F.col("t"), F.col("h"), F.col("w"))).alias("one"))
    b = b.withColumn("cells", (F.col("n") * F.col("one")).cast("bigint"))
    # batches are dealt to 16 streams by key, so no ordering runs over all of them in one task
    b = b.withColumn("stream", key_int(F.col("bucket_id"), "_", F.col("shard"), "_", F.col("batch_no")) % 16)
    seq = F.row_number().over(W.partitionBy("stream").orderBy("batch_no", "shard", "bucket_id")) - 1
    steps = b.withColumn("step", int_div(seq, 8)).groupBy("stream", "step").agg(F.count("*").alias("n"), F.max("cells").alias("most"), F.sum("cells").cast("bigint").alias("total"))
    return steps.agg(F.count("*").alias("steps"), F.sum(F.col("most") * F.col("n") - F.col("total")).cast("bigint").alias("wait"), F.sum("total").cast("bigint").alias("work"))


def bucket_vs_padmax(spark, d):
    """Latent cells computed by each arm for the same media: bucketed, one bucket, padded to the largest."""
    a = assigned(spark, d)
    own = B.latent_cells(F.col("t"), F.col("h"), F.col("w"))
    raw = B.latent_cells(F.col("frames"), F.col("height"), F.col("width"))
    one = a.agg(F.count("*").alias("n"), F.sum(own).cast("bigint").alias("bucketed"), F.max(raw).alias("largest"), F.sum(raw).cast("bigint").alias("needed"))
    single = 8 * 80 * 80  # the first bucket
    arms = F.array(F.struct(F.lit("bucketed").alias("arm"), F.col("bucketed").alias("cells")), F.struct(F.lit("single").alias("arm"), (F.col("n") * single).alias("cells")),
                   F.struct(F.lit("pad_to_max").alias("arm"), (F.col("n") * F.col("largest")).alias("cells")), F.struct(F.lit("native").alias("arm"), F.col("needed").alias("cells")))
    return one.select(F.explode(arms).alias("a")).select("a.arm", "a.cells")


def early_stop_point(spark, d):
    daily = T.load(spark, d, "events").groupBy(F.date_trunc("day", F.col("ts").cast("timestamp")).cast("date").cast("string").alias("t")).agg(rnd(F.avg("value"), 4).alias("v"))
    return C.early_stop(daily, 3)


def stage_tokens(spark, d):
    s = C.stage_plan(spark)
    vid = F.when(F.col("frames") > 0, B.latent_cells(F.col("frames"), F.col("video_res"), F.col("video_res"))).otherwise(0).cast("bigint")
    img = int_div(F.col("image_res"), 8) * int_div(F.col("image_res"), 8)
    return s.select("step_no", "stage", vid.alias("video_cells"), img.alias("image_cells"), int_div(vid, 4).alias("video_tokens"), int_div(img, 4).alias("image_tokens"))


def mix_schedule(spark, d):
    steps = spark.range(0, 1000, 50).select(F.col("id").alias("step"))
    return steps.select("step", rnd(C.image_share(F.col("step"), 1000)).alias("linear"), rnd(C.image_share(F.col("step"), 1000, shape="step")).alias("stepped"))


CONFIG = """{"image": [[4, 1, 320, 320], [1, 1, 640, 640]], "video": [[4, 29, 320, 320], [1, 61, 320, 320]],
  "joint": [[1, 1, 640, 640], [1, 61, 640, 640], [1, 125, 640, 640], [1, 125, 960, 960]]}"""


def stage_plan(spark, d):
    """Several bucket sets from one configuration file, a stage each, and the media that each bucket of a stage gets."""
    config, out, media = B.BucketConfig.from_json(CONFIG), None, T.media_meta(spark, d)
    for name, buckets in config.sets.items():
        n = B.assign_bucket(media, buckets).filter("bucket is not null").groupBy(F.col("bucket.id").alias("bucket_id")).agg(F.count("*").alias("media"))
        part = B.with_tokens(config.table(spark, name)).join(F.broadcast(n), "bucket_id", "left")  # n is a row a bucket
        part = part.select(F.lit(name).alias("set"), "bucket_id", "batch", "t", "h", "cells", F.coalesce("media", F.lit(0).cast("bigint")).alias("media"))
        out = part if out is None else out.unionByName(part)
    return out


def averaged(frames):
    return C.ema(frames, 0.9, ["media_id"], "frame_no", "luma")


QUERIES = {
    "bucket_assign": bucket_assign,
    "bucket_tokens": lambda s, d: bucket_media(s, d).select("bucket_id", "lt", "lh", "lw", "cells", "tokens", "media"),
    "bucket_assign_floor": by_rule("floor"), "bucket_assign_ceil": by_rule("ceil"), "bucket_assign_nearest": by_rule("nearest"),
    "bucket_assign_area": lambda s, d: assigned(s, d).select("media_id", "bucket_id"),
    "bucket_crop": lambda s, d: assigned(s, d).select("media_id", B.crop_start(F.col("media_id"), F.col("frames"), F.col("t")).alias("start")),
    "bucket_resize": lambda s, d: assigned(s, d).withColumn("scale", F.greatest(F.col("h") / F.col("height"), F.col("w") / F.col("width"))).select("media_id", rnd(F.col("scale")).alias("scale"),
        rnd(1 - F.col("h") * F.col("w") / (F.col("height") * F.col("width") * F.col("scale") * F.col("scale"))).alias("lost_share")),
    "bucket_tune_batch": bucket_tune_batch,
    "bucket_token_spread": bucket_token_spread,
    "bucket_batches": lambda s, d: batches(s, d).groupBy("bucket_id", "shard").agg(F.countDistinct("batch_no").alias("batches"), F.count("*").alias("n"), F.sum(F.col("media_id") * (F.col("batch_no") + 1)).cast("bigint").alias("check_sum")),
    "bucket_step_balance": bucket_step_balance, "bucket_vs_padmax": bucket_vs_padmax,
    "bucket_stage_plan": stage_plan,
    "stage_eligibility": lambda s, d: C.eligible(T.media_meta(s, d), C.stage_plan(s)).groupBy("step_no").agg(F.count("*").alias("n"), F.sum("media_id").cast("bigint").alias("ids")),
    "stage_samples_seen": lambda s, d: C.stage_plan(s).select("step_no", (F.col("batch") * F.col("steps")).alias("seen"), F.sum(F.col("batch") * F.col("steps")).over(W.orderBy("step_no")).cast("bigint").alias("seen_so_far")),
    "stage_tokens": stage_tokens, "mix_schedule": mix_schedule,
    "mix_assign": lambda s, d: C.mix_assign(T.media_meta(s, d), 1000).groupBy(int_div(F.col("step"), 100).alias("tenth")).agg(F.count("*").alias("n"), F.sum("as_image").cast("bigint").alias("images")),
    "early_stop_point": early_stop_point,
    "ema_series": lambda s, d: averaged(T.frames(s, d)).select("media_id", "frame_no", rnd(F.col("ema") + 1e-9, 4).alias("ema")),
    "inspection_points": lambda s, d: C.inspection_points(T.frames(s, d), 10, "frame_no").select("media_id", "frame_no", "luma"),
    "steps_to_converge": lambda s, d: C.steps_to_converge(averaged(T.frames(s, d)), 20.0, ["media_id"], "frame_no", "ema"),
    "epoch_account": lambda s, d: C.stage_plan(s).select("step_no", rnd(C.epochs(F.lit(500_000.0), F.col("batch"), F.col("steps"))).alias("epochs")),
}

_SHARD = h("cast(media_id as varchar) || 's'") + " % 8"
_BATCHED = f"""{FLOOR}, b as (select *, {_SHARD} as shard from a where k = 1),
  p as (select *, (row_number() over (partition by bucket_id, shard order by {h("cast(media_id as varchar) || 'o'")}, media_id) - 1) // batch as batch_no from b) """
_EMA = """e as (select a.media_id, a.frame_no, sum(case when b.frame_no = 1 then 1.0 else 0.1 end * b.luma * pow(0.9, a.frame_no - b.frame_no)) as ema
  from frames a join frames b on a.media_id = b.media_id and b.frame_no <= a.frame_no group by 1, 2) """


# media of each published bucket
_COUNTED = FLOOR + ", n as (select bucket_id, count(*) as media from a where k = 1 group by 1), c as (select b.*, coalesce(media, 0) as media from buckets b left join n using (bucket_id)) "


def _rule(expr: str) -> str:
    return using("media_meta", sql=f"f as (select *, {expr} as bucket_t from media_meta) select coalesce(bucket_t, 0) as bucket_t, count(*) as n, cast(sum(frames) as bigint) as frames from f group by 1")


GATE = "width * 10 >= height * 4 and width * 10 <= height * 25 and fps >= 16 and sample_rate >= 22050 and frames >= fps * 2 and status <> 'P'"
ORACLES = {
    "bucket_assign": using("media_meta", sql=f"""{LITERAL}, m as (select * from media_meta where {GATE}), f as (select *, (select max(t) from buckets where t <= frames) as bucket_t from m),
      a as (select f.media_id, f.frames, b.bucket_id, row_number() over (partition by media_id order by abs(b.h * b.w - height * width), abs(width * b.h - height * b.w), b.bucket_id) as k from f left join buckets b on b.t = f.bucket_t)
      select coalesce(bucket_id, -1) as bucket_id, count(*) as n, cast(sum(frames) as bigint) as frames from a where k = 1 group by 1"""),
    "bucket_tokens": _COUNTED + f"select bucket_id, 1 + (t - 1) // 4 as lt, h // 8 as lh, w // 8 as lw, batch * {CELLS} as cells, batch * (1 + (t - 1) // 4) * ((h // 8) // 2) * ((w // 8) // 2) as tokens, media from c",
    "bucket_assign_floor": _rule("case when frames >= 125 then cast(125 as bigint) when frames >= 29 then 29 end"),
    "bucket_assign_ceil": _rule("case when frames <= 29 then cast(29 as bigint) when frames <= 125 then 125 end"),
    "bucket_assign_nearest": _rule("case when abs(frames - 29) <= abs(frames - 125) then cast(29 as bigint) else 125 end"),
    "bucket_assign_area": FLOOR + "select media_id, bucket_id from a where k = 1",
    "bucket_crop": FLOOR + "select media_id, " + h("cast(media_id as varchar) || 'c'") + " % (frames - t + 1) as start from a where k = 1",
    "bucket_resize": FLOOR + "select media_id, round(s, 6) + 0.0 as scale, round(1 - h * w / (height * width * s * s), 6) + 0.0 as lost_share from (select *, greatest(h / height, w / width) as s from a where k = 1)",
    "bucket_tune_batch": _COUNTED + f", e as (select bucket_id, greatest(1, {BUDGET} // ({CELLS})) as tuned, media from c) select bucket_id, tuned, media, (media + tuned - 1) // tuned as batches from e",
    "bucket_token_spread": FLOOR + f", c as (select batch * {CELLS} as cells from a where k = 1) select count(*) as media, min(cells) as least, max(cells) as most, round(max(cells) / min(cells), 6) as spread from c",
    "bucket_batches": _BATCHED + "select bucket_id, shard, count(distinct batch_no) as batches, count(*) as n, cast(sum(media_id * (batch_no + 1)) as bigint) as check_sum from p group by 1, 2",
    "bucket_step_balance": _BATCHED + f""", q as (select bucket_id, shard, batch_no, count(*) * any_value({CELLS}) as cells from p group by 1, 2, 3),
      r as (select *, {h("cast(bucket_id as varchar) || '_' || cast(shard as varchar) || '_' || cast(batch_no as varchar)")} % 16 as stream from q),
      s as (select *, (row_number() over (partition by stream order by batch_no, shard, bucket_id) - 1) // 8 as step from r),
      t_ as (select stream, step, count(*) as n, max(cells) as most, sum(cells) as total from s group by 1, 2)
      select count(*) as steps, cast(sum(most * n - total) as bigint) as wait, cast(sum(total) as bigint) as work from t_""",
    "bucket_vs_padmax": FLOOR + f""", one as (select count(*) as n, sum({CELLS}) as bucketed, sum((1 + (frames - 1) // 4) * (height // 8) * (width // 8)) as needed, max((1 + (frames - 1) // 4) * (height // 8) * (width // 8)) as largest from a where k = 1)
      select 'bucketed' as arm, cast(bucketed as bigint) as cells from one union all select 'single', n * 51200 from one union all select 'pad_to_max', n * largest from one union all select 'native', cast(needed as bigint) from one""",
    "bucket_stage_plan": using("media_meta", sql="""v(k, i, n, t, r) as (values ('image', 0, 4, 1, 320), ('image', 1, 1, 1, 640), ('video', 0, 4, 29, 320), ('video', 1, 1, 61, 320), ('joint', 0, 1, 1, 640), ('joint', 1, 1, 61, 640), ('joint', 2, 1, 125, 640), ('joint', 3, 1, 125, 960)),
      f as (select media_id, height, width, k, max(t) as bucket_t from media_meta join v on t <= frames group by 1, 2, 3, 4),
      g as (select f.k, media_id, arg_min(i, struct_pack(d := abs(r * r - height * width), s := abs(width * r - height * r), i := i)) as i from f join v on v.k = f.k and v.t = bucket_t group by 1, 2), n as (select k, i, count(*) as media from g group by 1, 2)
      select v.k as "set", cast(v.i as bigint) as bucket_id, cast(v.n as bigint) as batch, cast(t as bigint) as t, cast(r as bigint) as h, cast(v.n * (1 + (t - 1) // 4) * (r // 8) * (r // 8) as bigint) as cells, coalesce(media, 0) as media from v left join n on n.k = v.k and n.i = v.i"""),
    "stage_eligibility": using("media_meta", sql=f"""{STAGE_LIT} select step_no, count(*) as n, cast(sum(media_id) as bigint) as ids from media_meta join stages on
      (frames = 1 and image_res > 0 and least(height, width) >= image_res) or (s_frames > 0 and frames >= s_frames and least(height, width) >= video_res) group by 1"""),
    "stage_samples_seen": f"with {STAGE_LIT} select a.step_no, a.batch * a.steps as seen, cast((select sum(b.batch * b.steps) from stages b where b.step_no <= a.step_no) as bigint) as seen_so_far from stages a",
    "stage_tokens": f"""with {STAGE_LIT}, c as (select step_no, stage, case when s_frames > 0 then (1 + (s_frames - 1) // 4) * (video_res // 8) * (video_res // 8) else 0 end as video_cells, (image_res // 8) * (image_res // 8) as image_cells from stages)
      select *, video_cells // 4 as video_tokens, image_cells // 4 as image_tokens from c""",
    "mix_schedule": "select cast(i * 50 as bigint) as step, round(0.3 + (0.1 - 0.3) * (i * 50) / 999.0, 6) as linear, case when i * 100 < 1000 then cast(0.3 as double) else 0.1 end as stepped from range(20) t(i)",
    "mix_assign": using("media_meta", sql=f"""s as (select {h("cast(media_id as varchar) || 'step'")} % 1000 as step, {h("cast(media_id as varchar) || 'kind'")} as k from media_meta)
      select step // 100 as tenth, count(*) as n, count(*) filter (k < (cast(0.3 as double) + (cast(0.1 as double) - cast(0.3 as double)) * step / 999.0) * 4294967296.0) as images from s group by 1"""),
    "early_stop_point": """with d as (select cast(cast(ts as date) as varchar) as t, round(avg(value), 4) as v from events group by 1), r as (select *, row_number() over (order by t) as n from d),
      b as (select r.t, r.n, (select min(v) from r x where x.n <= r.n) as best from r), l as (select b.*, (select max(x.n) from r x join b y on x.n = y.n where x.n <= b.n and x.v = y.best) as low_at from b)
      select min(t) filter (n - low_at >= 3) as stop_at, arg_min(best, t) filter (n - low_at >= 3) as best from l""",
    "ema_series": using("frames", sql=_EMA + "select media_id, frame_no, round(ema + 1e-9, 4) as ema from e"),
    "inspection_points": using("frames", sql="select media_id, frame_no, luma from frames where frame_no % 10 = 0"),
    "steps_to_converge": using("frames", sql=_EMA + """, l as (select media_id, arg_max(ema, frame_no) as final from e group by 1), g as (select e.media_id, frame_no, abs(ema - final) as gap from e join l using (media_id))
      select a.media_id, min(a.frame_no) filter (not exists (select 1 from g b where b.media_id = a.media_id and b.frame_no >= a.frame_no and b.gap > 20.0)) as converged_at from g a group by 1"""),
    "epoch_account": f"with {STAGE_LIT} select step_no, round(batch * steps / 500000.0, 6) as epochs from stages",
}
