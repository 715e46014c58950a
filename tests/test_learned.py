"""The learned predictors: gradients, integer inference, wavefront decoding, training on Spark tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from shotgrid import workloads
from shotgrid.operators import anchor, codec, learned
from shotgrid.sources import images

SF = "/root/testdata/sf0.001"


def contexts(spec, seed=0, n=8):
    rng = np.random.default_rng(seed)
    code, valid = rng.integers(50, 80, (1, 12, 12)), rng.random((1, 12, 12)) < 0.8
    i, j = rng.integers(1, 12, n), rng.integers(1, 12, n)
    return anchor.patch(spec, code, valid, np.zeros(n, int), i, j), rng


@pytest.mark.parametrize("head", anchor.HEADS)
def test_gradients_by_finite_differences(head):
    spec = anchor.NetSpec(context=(3, 3), head=head, width=0.1)
    p, rng = contexts(spec)
    net = anchor.build(spec, 1)
    for n in net.b:
        net.b[n] = rng.normal(0, 0.1, net.b[n].shape)
    s = anchor.samples_of(p, rng.random(8) * 7 + 3, 0.1, spec)
    _, grads = net.loss(s, 0.5)
    for n in net.w:
        for part, store in ((0, net.w), (1, net.b)):
            if part and n.endswith("l"):
                continue
            at = tuple(rng.integers(0, d) for d in store[n].shape)
            old, e = store[n][at], 1e-6
            store[n][at] = old + e
            up = net.loss(s, 0.5)[0]
            store[n][at] = old - e
            down = net.loss(s, 0.5)[0]
            store[n][at] = old
            assert (up - down) / 2 / e == pytest.approx(grads[n][part][at], abs=1e-5, rel=1e-3)


@pytest.mark.parametrize("head", anchor.HEADS)
def test_frozen_predictions_do_not_depend_on_the_batch(head):
    spec = anchor.NetSpec(context=(4, 4), head=head, width=0.2)
    p, _ = contexts(spec, 3, 40)
    net = anchor.build(spec, 2).freeze()
    whole = net.predict(p, 0.1)
    assert [int(net.predict({k: v[i : i + 1] for k, v in p.items()}, 0.1)[0]) for i in range(40)] == whole.tolist()
    assert all((w == np.floor(w)).all() for w in net.w.values())
    again = anchor.Net.loads(net.dumps())
    assert again.model_id == net.model_id and (again.predict(p, 0.1) == whole).all()


def test_wavefront_gives_the_codes_back():
    rng = np.random.default_rng(4)
    net = anchor.build(anchor.NetSpec(context=(3, 4), width=0.1), 5).freeze()
    code, valid = rng.integers(0, 300, (3, 6, 9)), rng.random((3, 6, 9)) < 0.7
    code, zero = np.where(valid, code, 0), np.zeros(3, int)
    delta = np.where(valid, code - codec._learned(net, code, valid, 0.1, zero, zero), 0)
    assert (anchor.wavefront(net, delta, valid, 0.1, zero, zero) == code).all()


def test_labels_prefer_near_angles_and_pixels_without_context_predict_zero():
    spec = anchor.NetSpec(context=(2, 2))
    code, valid = np.array([[[5, 9], [5, 5]]]), np.ones((1, 2, 2), bool)
    p = anchor.patch(spec, code, valid, np.zeros(2, int), np.array([1, 0]), np.array([1, 0]))
    s = anchor.samples_of(p, np.array([0.5, 0.5]), 0.1, spec)
    di, dj = spec.offsets
    assert (di[s["label"][0]], dj[s["label"][0]]) == (0, 1) or (di[s["label"][0]], dj[s["label"][0]]) == (1, 0) and p["value"][0, s["label"][0]] == 5
    assert anchor.build(spec).freeze().predict(p, 0.1)[1] == 0


def test_training_lowers_the_loss_and_sums_of_gradients_agree(spark):
    px = images.scene(spark, SF, frames=2)
    spec, how = workloads.spec_of(context=(3, 3), width=0.1), codec.CodecSpec(0.1, "learned", (25, 240), gop=2)
    rows = learned.samples(px, how, spec, every=11).repartition(3).cache()
    data = learned.held(rows)
    net, history = anchor.fit(spec, learned.drawer(data, spec, 0.1), 80, 64, 5e-3)
    assert np.mean(history[-10:]) < 0.7 * np.mean(history[:10])
    whole = learned.batch(data, np.arange(len(data["target"])), spec, 0.1, False)
    _, want = net.loss(whole)
    for r in learned.gradient_sums(rows, net).collect():
        assert np.array(r.value) / r.n == pytest.approx(want[r.name][r.part].ravel(), abs=1e-9)
    assert learned.train_on_cluster(rows, spec, 2, 5e-3).loss(whole)[0] < anchor.build(spec).loss(whole)[0]


def test_another_model_is_refused(spark):
    px = images.scene(spark, SF, frames=1).where("row < 4 and col < 20")
    how = codec.CodecSpec(0.1, "learned", (4, 20))
    a, b = (anchor.build(anchor.NetSpec(context=(2, 2), width=0.1), s).freeze() for s in (1, 2))
    with pytest.raises(Exception, match="model"):
        codec.decode(codec.encode(px, how, a), b).collect()


def test_void_frames_and_repeated_pixels(spark):
    schema = "frame_id long, row int, col int, range double"
    px = spark.createDataFrame([(0, 0, 0, 1.0), (0, 1, 3, None), (1, 0, 0, None)], schema)
    got = codec.encode(px, codec.CodecSpec(0.1, "left"), size=(4, 8))
    assert [tuple(r) for r in codec.headers(got).orderBy("frame_id").collect()] == [(0, 4, 8, 1), (1, 4, 8, 0)]
    assert [(r.frame_id, r.code) for r in codec.decode(got).collect()] == [(0, 10)]
    with pytest.raises(Exception, match="twice"):
        codec.encode(spark.createDataFrame([(0, 0, 0, 1.0), (0, 0, 0, 2.0)], schema)).collect()


def test_one_exchange_builds_the_blocks(spark):
    plan = codec.encode(images.part_img(spark, SF), codec.CodecSpec())._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "CartesianProduct" not in plan


def test_mixed_precisions_are_even(spark):
    d = [r.d for r in spark.range(20_000).select(learned.sample_precision(["id"]).alias("d")).collect()]
    assert min(d) >= 1e-4 and max(d) <= 0.5 and abs(np.mean(d) - 0.25) < 0.01 and F is not None
