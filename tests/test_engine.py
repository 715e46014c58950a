import glob
import os

import duckdb
import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from shotgrid import registry
from shotgrid.operators import codec, coders, linear, measures

SF = "/root/testdata/sf0.001"


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(-5, 5) | st.integers(-(10**6), 10**6), max_size=80))
def test_coders_round_trip(values):
    x = np.array(values, np.int64)
    for name, (pack, unpack) in coders.CODERS.items():
        assert unpack(pack(x)).tolist() == values, name


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 6), st.integers(1, 7), st.integers(0, 2**31))
def test_block_predictors_invert(h, w, seed):
    rng = np.random.default_rng(seed)
    code, valid = rng.integers(0, 750, (h, w)), rng.random((h, w)) < 0.7
    code = np.where(valid, code, 0)
    for kind in ("none", "left", "three"):
        delta = np.where(valid, code - codec.predict(code, valid, kind), 0)
        assert (codec.restore(delta, valid, kind)[valid] == code[valid]).all()


def test_worked_image(spark):
    """A 2 x 4 image: deltas, accuracy and entropy by hand."""
    px = spark.createDataFrame([(0, 0, c, v) for c, v in enumerate((10.0, 10.04, 10.16))] + [(0, 1, c, v) for c, v in enumerate((10.02, 10.11, 30.0, 30.04))], "frame_id long, row int, col int, range double")
    q = linear.codes(px, 0.1)
    got = {k: [r.delta for r in linear.PREDICTORS[k](q).orderBy("row", "col").collect()] for k in ("left", "three")}
    assert got == {"left": [100, 0, 2, 100, 1, 199, 0], "three": [100, 0, 2, 0, 1, 197, 0]}
    assert measures.accuracy(linear.delta_three(q)).first().accuracy == pytest.approx(300 / 7, abs=1e-5)
    assert measures.entropy_h0(linear.delta_left(q)).first().h0 == pytest.approx(2.23593, abs=1e-5)
    assert coders.varints(coders.zigzag(np.array(got["three"]))).hex() == "c801000400028a0300"
    assert [r.code for r in linear.undo_three(linear.delta_three(q)).orderBy("row", "col").collect()] == [100, 100, 102, 100, 101, 300, 300]


def test_bad_checksum_raises(spark):
    from pyspark.sql import functions as F

    px = spark.createDataFrame([(0, 0, 0, 1.0), (0, 0, 1, 2.0)], "frame_id long, row int, col int, range double")
    with pytest.raises(Exception, match="checksum"):
        codec.decode(codec.encode(px).withColumn("crc", F.lit(1).cast("long"))).collect()


@pytest.mark.parametrize("name", ["join_asof_pose", "rle_runs", "rate_cube", "unproject_scene", "knn_topk", "psnr_given_normals", "kdtree_roundtrip", "png16_roundtrip", "codec_roundtrip_multi", "stream_frames", "stream_prev_delta", "scan_container", "udtf_decode", "scene_image", "delta_three_scene_01", "undelta_three_events_01", "entropy_left_part_01", "codec_roundtrip_three_16x50_scene_01", "nn_voxel", "chamfer_sym", "octree_occupancy", "average_precision"])
def test_against_sql(spark, name):
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    df, q = registry.queries()[name](spark, SF), con.execute(registry.oracle_sql()[name])
    names = [d[0] for d in q.description]
    cols = sorted(df.columns)
    assert sorted(names) == cols
    want = sorted((tuple(r[names.index(c)] for c in cols) for r in q.fetchall()), key=str)
    assert sorted((tuple(r[c] for c in cols) for r in df.collect()), key=str) == want


def test_three_neighbour_wins_on_the_scene(spark):
    rate = {k: registry.queries()[f"entropy_{k}_scene_01"](spark, SF).first().h0 for k in ("none", "left", "three")}
    assert rate["three"] < rate["left"] < rate["none"]


def test_nearest_keeps_points_of_frames_without_partners(spark):
    p = spark.createDataFrame([(0, 1, 0.0, 0.0, 0.0), (1, 2, 0.0, 0.0, 0.0)], "frame_id long, id long, x double, y double, z double")
    q = spark.createDataFrame([(0, 9, 3.0, 4.0, 0.0)], p.schema)
    assert {(r.frame_id, r.id, r.dist) for r in measures.nearest(p, q, 1.0).collect()} == {(0, 1, 5.0), (1, 2, None)}
    assert {(r.frame_id, r.id, r.dist) for r in measures.nearest(p, q, 1.0, rounds=1).collect()} == {(0, 1, 5.0), (1, 2, None)}
