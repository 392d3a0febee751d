"""The stand-in views in DuckDB SQL, as common table expressions for the oracles."""

from __future__ import annotations

H = "cast(('0x' || substr(md5({}), 1, 8)) as bigint)"


def h(expr: str) -> str:
    """The keyed whole number of exprs.key_int."""
    return H.format(expr)


def uniform(expr: str) -> str:
    return f"(cast({h(expr)} + 1 as double) / 4294967298.0)"


def gauss(expr: str) -> str:
    return f"(round(sqrt(-2.0 * ln({uniform(f'{expr} || chr(97)')})) * cos(2 * pi() * {uniform(f'{expr} || chr(98)')}), 6) + 0.0)"


VIEWS = {
    "media_meta": """select o_orderkey as media_id, cast(floor(o_totalprice) as bigint) % 160 + 1 as frames, 16 * (o_custkey % 60 + 15) as height,
        16 * (cast(floor(o_totalprice / 7) as bigint) % 100 + 20) as width, cast(dayofyear(o_orderdate) as bigint) % 53 + 8 as fps,
        cast(case substr(o_orderpriority, 1, 1) when '1' then 48000 when '2' then 44100 when '3' then 22050 when '4' then 16000 else 8000 end as bigint) as sample_rate,
        o_orderstatus as status from orders""",
    "frames": """select user_id as media_id, row_number() over (partition by user_id order by ts, event_id) as frame_no, value as luma,
        cast(json_extract_string(props, '$.k') as bigint) as texture, event_type as kind, ts, event_id from events""",
    "planted_hard": """select media_id, frame_no, luma + 300.0 * (((frame_no - 1) // 12) % 2) as luma, (frame_no - 1) // 12 > 0 and (frame_no - 1) % 12 = 0 as true_cut from frames""",
    "planted_ramp": """select media_id, frame_no, luma + case when seg > 0 and pos <= 3 then 300.0 * ((seg + 1) % 2) + (300.0 * (seg % 2) - 300.0 * ((seg + 1) % 2)) * (pos + 1) / 5 else 300.0 * (seg % 2) end as luma,
        seg > 0 and pos = 0 as true_cut from (select *, (frame_no - 1) // 12 as seg, (frame_no - 1) % 12 as pos from frames)""",
    "clips": """select l_orderkey as video_id, cast(l_linenumber as bigint) as clip_no, cast(floor(max(l_quantity)) as bigint) % 160 * 4 + 1 as n_frames,
        cast(floor(max(l_extendedprice)) as bigint) % 100 as body, max((l_partkey + l_suppkey) % 100) as face,
        max(cast(round(l_discount * 100) as bigint)) * 9 as appeal, max(cast(round(l_tax * 100) as bigint)) * 12 as clarity,
        cast(floor(max(l_quantity)) as bigint) * 2 as occlusion, min(l_returnflag) as flag from lineitem group by 1, 2""",
    "text_clips": """select doc_id, cast(pos - 1 as bigint) as clip_no, line, cast(length(line) as bigint) as len, lang, source from
        (select doc_id, lang, source, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) as pos from documents)""",
    "turn_clips": "select conv_id as video_id, turn as clip_no, role, text from conversations",
    "review": "select doc_id, cast(quality as bigint) as quality, cast(toxic as bigint) as toxic, " + ", ".join(
        "cast(case when " + h(f"cast(doc_id as varchar) || '{i}'") + f" % 10 = 0 then 1 - quality else quality end as bigint) as v{i}" for i in range(1, 5)) + " from labels",
    "cells": "select vec_id as item, label, unnest(embedding) as v, cast(generate_subscripts(embedding, 1) - 1 as bigint) as i from embeddings",
    "latents": "select item, i, i // 16 as t, (i // 4) % 4 as y, i % 4 as x, cast(v as double) as val from cells",
    "latents88": "select item, i, i // 8 as y, i % 8 as x, cast(v as double) as val from cells",
    "telemetry": """select event_id, user_id % 64 as rank, case event_type when 'view' then 'forward' when 'click' then 'backward' when 'purchase' then 'update'
        when 'signup' then 'data' when 'error' then 'communication' end as phase, value as ms, ts from events""",
    "topology": """select s_suppkey as node, cast(n_nationkey as bigint) as rack, cast(r_regionkey as bigint) as pod
        from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey""",
}
NEEDS = {"planted_hard": ("frames",), "planted_ramp": ("frames",), "latents": ("cells",), "latents88": ("cells",)}


def using(*names: str, sql: str) -> str:
    """``sql`` (which may begin with further CTEs, without the word with) behind the named views."""
    order: list[str] = []
    for n in names:
        order += [x for x in (*NEEDS.get(n, ()), n) if x not in order]
    head = ", ".join(f"{n} as ({VIEWS[n]})" for n in order)
    body = sql.strip()
    return f"with {head}{' ' if body.lower().startswith('select') else ', '}{body}"
