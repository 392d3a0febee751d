"""Queries cover all rows of their tables."""

import numpy as np
import pytest

from clipforge import queries

QUERIES, ORACLES = queries.load()


def rows(duck, sql):
    return duck.execute(sql).fetchone()[0]


@pytest.mark.parametrize("name", ["attention_full", "attention_sparse_stride", "attention_sparse_block", "attention_separated", "joint_attention"])
def test_every_cell_is_attended(spark, sf, duck, name):
    got = QUERIES[name](spark, sf)
    assert got.count() == rows(duck, "select sum(len(embedding)) from embeddings")
    assert got.select("item").distinct().count() == rows(duck, "select count(distinct vec_id) from embeddings") > 50


@pytest.mark.parametrize("name", ["rope3d_rotate", "time_condition"])
def test_every_vector_is_turned(spark, sf, duck, name):
    assert QUERIES[name](spark, sf).count() == rows(duck, "select count(*) from embeddings") > 100


def test_frechet_takes_all_features(spark, sf, duck):
    rows_ = duck.execute("select vec_id, embedding from embeddings").fetchall()
    a, b = (np.array([e for i, e in rows_ if i % 2 == k], float) for k in (0, 1))
    ca, cb = (np.cov(x.T, bias=True) for x in (a, b))
    root = np.sqrt(np.maximum(np.linalg.eigvals(ca @ cb).real, 0)).sum()
    want = ((a.mean(0) - b.mean(0)) ** 2).sum() + np.trace(ca) + np.trace(cb) - 2 * root
    assert QUERIES["metric_frechet_full"](spark, sf).collect()[0].frechet == pytest.approx(want, abs=1e-5)


def test_series_go_on_to_their_end(spark, sf, duck):
    got = QUERIES["ema_series"](spark, sf)
    assert got.count() == rows(duck, "select count(*) from events")
    assert got.agg({"frame_no": "max"}).collect()[0][0] > 40


def test_every_parameter_drifts(spark, sf, duck):
    assert QUERIES["param_drift"](spark, sf).count() == rows(duck, "select count(*) from events") > 50
