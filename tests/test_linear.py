import numpy as np

from shotgrid.operators import codec, linear


def test_three_neighbour_reads_valid_pixels_only(spark):
    """Equal to the predictor on a filled array, inverts, and lays out no void pixel: a plan without joins or generated rows."""
    rng = np.random.default_rng(3)
    code, valid = rng.integers(0, 750, (3, 9, 11)), rng.random((3, 9, 11)) < 0.5
    valid[0, 4] = valid[1, :, 3] = False  # a void row and a void column
    at = np.argwhere(valid)
    px = spark.createDataFrame([(int(f), int(r), int(c), int(code[f, r, c])) for f, r, c in at] + [(None, 0, 0, 5)], "frame_id long, row int, col int, code long")
    for block in (None, (4, 5)):
        want = {}
        h, w = block or (9, 11)
        for f in range(3):
            for r0 in range(0, 9, h):
                for c0 in range(0, 11, w):
                    v = valid[f, r0 : r0 + h, c0 : c0 + w]
                    x = np.where(v, code[f, r0 : r0 + h, c0 : c0 + w], 0)
                    d = x - codec.predict(x, v, "three")
                    want |= {(f, r0 + int(r), c0 + int(c)): int(d[r, c]) for r, c in np.argwhere(v)}
        assert {(p.frame_id, p.row, p.col): p.delta for p in linear.delta_three(px, block=block).collect()} == want
    back = linear.undo_three(linear.delta_three(px).drop("code"))
    assert {(p.frame_id, p.row, p.col): p.code for p in back.collect()} == {(f, r, c): int(code[f, r, c]) for f, r, c in at.tolist()}
    plan = back._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Generate" not in plan
