"""All registered queries of the engine with their DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import baselines, codec, geometry, linear, measures
from . import workloads
from .plans import relational
from .sources import images
from .sources.images import IMAGES, SQL
from .workloads import cloud_points, coarse_points

MAIN = ("scene", "part", "lineitem", "events")
FILL = """full_ AS (SELECT b.frame_id, r.row::INT AS row, c.col::INT AS col FROM (SELECT frame_id, min(row) r0, max(row) r1, min(col) c0, max(col) c1 FROM q GROUP BY 1) b, LATERAL (SELECT unnest(generate_series(r0, r1)) AS row) r, LATERAL (SELECT unnest(generate_series(c0, c1)) AS col) c),
    f AS (SELECT frame_id, row, col, code, coalesce(last_value(code IGNORE NULLS) OVER (PARTITION BY frame_id, row ORDER BY col ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 0) AS plane FROM full_ LEFT JOIN q USING (frame_id, row, col)),
    g AS (SELECT *, coalesce(lag(plane) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS l, coalesce(lag(plane) OVER (PARTITION BY frame_id, col ORDER BY row), 0) AS u FROM f),
    n AS (SELECT *, coalesce(lag(l) OVER (PARTITION BY frame_id, col ORDER BY row), 0) AS ul FROM g)"""


def q_sql(image: str, d: float, keep: str = "") -> str:
    return f"WITH px AS ({SQL[image]}), q AS (SELECT frame_id, row, col, {keep} floor(range / {d:e} + 5e-1)::BIGINT AS code FROM px)"


def delta_sql(image: str, d: float, kind: str) -> str:
    head = q_sql(image, d)
    if kind == "none":
        return f"{head}, z AS (SELECT *, code AS delta FROM q)"
    if kind == "left":
        return f"{head}, z AS (SELECT *, code - coalesce(lag(code) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS delta FROM q)"
    if kind == "prev_frame":
        return f"{head}, z AS (SELECT *, code - coalesce(lag(code) OVER (PARTITION BY row, col ORDER BY frame_id), 0) AS delta FROM q)"
    pred = {"three": "l + u - ul", "up": "u", "mean": "floor((l + u) / 2)::BIGINT", "gradient": "CASE WHEN abs(u - ul) <= abs(l - ul) AND abs(u - ul) <= abs(l + u - 2 * ul) THEN l WHEN abs(l - ul) <= abs(l + u - 2 * ul) THEN u ELSE ul END"}[kind]
    return f"{head}, {FILL}, z AS (SELECT frame_id, row, col, code, code - ({pred}) AS delta FROM n WHERE code IS NOT NULL)"


_ALL: dict[str, tuple] = {}


def _add(name: str, query, sql: str | None = None) -> None:
    _ALL[name] = (query, sql)


def _coded(image: str, d: float):
    return lambda s, p: linear.codes(IMAGES[image](s, p), d)


def _register() -> None:
    for image in IMAGES:
        _add(f"{image}_image", lambda s, p, f=IMAGES[image]: f(s, p), SQL[image])
        for d in (0.1, 0.02):
            name = f"{image}_{str(d).replace('0.', '0')}"
            _add(f"quantize_{name}", _coded(image, d), f"{q_sql(image, d)} SELECT * FROM q")
    for image in MAIN:
        for d in (0.1, 0.02):
            tag = f"{image}_{str(d).replace('0.', '0')}"
            for kind, predictor in linear.PREDICTORS.items():
                z = delta_sql(image, d, kind)
                if d == 0.1:
                    _add(f"delta_{kind}_{tag}", lambda s, p, c=_coded(image, d), f=predictor: f(c(s, p)).select("frame_id", "row", "col", "code", "delta"), f"{z} SELECT frame_id, row, col, code, delta FROM z")
                    _add(f"accuracy_{kind}_{tag}", lambda s, p, c=_coded(image, d), f=predictor: measures.accuracy(f(c(s, p))), f"{z} SELECT round(100 * sum((delta = 0)::BIGINT) / count(*), 6) AS accuracy, count(*) AS n_valid FROM z")
                _add(f"entropy_{kind}_{tag}", lambda s, p, c=_coded(image, d), f=predictor: measures.entropy_h0(f(c(s, p))), f"{z} SELECT round(-sum(n / t * log2(n / t)), 6) AS h0, sum(n)::BIGINT AS n_valid FROM (SELECT n, sum(n) OVER () AS t FROM (SELECT count(*) AS n FROM z GROUP BY delta))")
            for kind, undo in (("left", linear.undo_left), ("three", linear.undo_three), ("prev_frame", linear.undo_prev_frame)):
                if d == 0.1:
                    _add(f"undelta_{kind}_{tag}", lambda s, p, c=_coded(image, d), f=linear.PREDICTORS[kind], u=undo: u(f(c(s, p)).drop("code")).select("frame_id", "row", "col", "code"), f"{q_sql(image, d)} SELECT * FROM q")
            _add(f"residual_hist_{tag}", lambda s, p, c=_coded(image, d): measures.residual_histogram(linear.delta_three(c(s, p))), f"{delta_sql(image, d, 'three')} SELECT greatest(-20, least(20, delta))::BIGINT AS delta, count(*) AS n FROM z GROUP BY 1")
            _add(f"displacement_{tag}", lambda s, p, i=IMAGES[image], d=d: measures.displacement(i(s, p), d), f"WITH px AS ({SQL[image]}), e AS (SELECT abs(floor(range / {d:e} + 5e-1)::BIGINT * {d:e} - range) AS e FROM px) SELECT round(avg(e), 6) AS mean_error, round(max(e), 6) AS max_error, count(*) AS n_valid FROM e")
            for kind in ("none", "left", "three"):
                if d == 0.1:
                    for block in ((16, 50), (16, 25), (16, 26)):
                        if kind == "three" or block == (16, 50):
                            spec = codec.CodecSpec(d, kind, block)
                            _add(f"codec_roundtrip_{kind}_{block[0]}x{block[1]}_{tag}", lambda s, p, i=IMAGES[image], c=spec: codec.decode(codec.encode(i(s, p), c)).select("frame_id", "row", "col", "code"), f"{q_sql(image, d)} SELECT * FROM q")
        for coder in codec.coders.CODERS:
            if image in ("scene", "part"):
                _add(f"coder_roundtrip_{coder}_{image}", lambda s, p, i=IMAGES[image], c=codec.CodecSpec(0.1, "three", (32, 64), coder): codec.decode(codec.encode(i(s, p), c)).select("frame_id", "row", "col", "code"), f"{q_sql(image, 0.1)} SELECT * FROM q")
    _add("entropy_ctx_scene", lambda s, p: measures.entropy_ctx(linear.delta_three(linear.codes(images.scene(s, p), 0.1))), f"""{delta_sql("scene", 0.1, "three")}, k AS (SELECT delta, CASE WHEN a = 0 THEN 0 WHEN a <= 2 THEN 1 ELSE 2 END AS ctx FROM (SELECT delta, abs(coalesce(lag(delta) OVER (PARTITION BY frame_id, row ORDER BY col), 0)) AS a FROM z)),
        e AS (SELECT ctx, sum(n) AS n, round(-sum(n / t * log2(n / t)), 6) AS h FROM (SELECT ctx, n, sum(n) OVER (PARTITION BY ctx) AS t FROM (SELECT ctx, delta, count(*) AS n FROM k GROUP BY 1, 2)) GROUP BY ctx) SELECT round(sum(h * n) / sum(n), 5) AS h_ctx, sum(n)::BIGINT AS n_valid FROM e""")
    cloud = "SELECT label::BIGINT AS frame_id, vec_id AS id, 60e0 * embedding[1]::DOUBLE AS x, 60e0 * embedding[2]::DOUBLE AS y, 60e0 * embedding[3]::DOUBLE AS z FROM embeddings"
    coarse = f"SELECT frame_id, id, floor(x / 1e0 + 5e-1) * 1e0 AS x, floor(y / 1e0 + 5e-1) * 1e0 AS y, floor(z / 1e0 + 5e-1) * 1e0 AS z FROM ({cloud})"
    far = lambda a, b: f"SELECT a.frame_id, a.id, min(sqrt((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) + (a.z - b.z) * (a.z - b.z))) AS dist FROM ({a}) a JOIN ({b}) b USING (frame_id) GROUP BY 1, 2"
    _add("cloud3_points", cloud_points, cloud)
    _add("nn_voxel", lambda s, p: geometry.nearest(cloud_points(s, p), coarse_points(s, p), 4.0).select("frame_id", "id", F.round("dist", 6).alias("dist")), f"SELECT frame_id, id, round(dist, 6) AS dist FROM ({far(cloud, coarse)})")
    _add("chamfer_oneway", lambda s, p: measures.chamfer_oneway(cloud_points(s, p), coarse_points(s, p), 4.0), f"SELECT frame_id, round(avg(dist), 6) AS chamfer, count(*) AS n FROM ({far(cloud, coarse)}) GROUP BY 1")
    _add("chamfer_sym", lambda s, p: measures.chamfer_sym(cloud_points(s, p), coarse_points(s, p), 4.0), f"SELECT frame_id, greatest(a.c, b.c) AS chamfer FROM (SELECT frame_id, round(avg(dist), 6) AS c FROM ({far(cloud, coarse)}) GROUP BY 1) a JOIN (SELECT frame_id, round(avg(dist), 6) AS c FROM ({far(coarse, cloud)}) GROUP BY 1) b USING (frame_id)")
    cell = lambda c: f"greatest(0, least(63, floor(({c} + 64e0) / 2e0)))::BIGINT"
    key = " | ".join(f"((({c} >> {i}) & 1) << {3 * i + k})" for k, c in enumerate("xyz") for i in range(6))
    leaves = f"l6 AS (SELECT DISTINCT frame_id, ({key}) AS key FROM (SELECT frame_id, {cell('x')} AS x, {cell('y')} AS y, {cell('z')} AS z FROM ({cloud})))"
    up = ", ".join(f"l{n} AS (SELECT frame_id, key >> 3 AS key, bit_or((1 << (key & 7))::BIGINT) AS byte FROM l{n + 1} GROUP BY 1, 2)" for n in range(5, -1, -1))
    nodes = " UNION ALL ".join(f"SELECT frame_id, {n} AS level, key, byte FROM l{n}" for n in range(6))
    _add("octree_occupancy", lambda s, p: baselines.octree_occupancy(baselines.voxels(cloud_points(s, p), 6, 128.0), 6), f"WITH {leaves}, {up} {nodes}")
    _add("png_filters_scene", lambda s, p: baselines.png_filters(images.scene(s, p), 100.0), f"WITH px AS ({SQL['scene']}), v AS (SELECT frame_id, row, col, least(65535, floor(range * 1e2 + 5e-1))::BIGINT AS v FROM px), w AS (SELECT *, coalesce(lag(v) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS l, coalesce(lag(v) OVER (PARTITION BY frame_id, col ORDER BY row), 0) AS u FROM v) SELECT frame_id, row, sum(v)::BIGINT AS none, sum(abs(v - l))::BIGINT AS \"left\", sum(abs(v - u))::BIGINT AS up FROM w GROUP BY 1, 2")
    _add("fieldwise_delta", lambda s, p: baselines.fieldwise_delta(cloud_points(s, p), 0.1, ["id"]), f"SELECT frame_id, id, x - coalesce(lag(x) OVER w, 0) AS dx, y - coalesce(lag(y) OVER w, 0) AS dy, z - coalesce(lag(z) OVER w, 0) AS dz FROM (SELECT frame_id, id, floor(x / 1e-1 + 5e-1)::BIGINT AS x, floor(y / 1e-1 + 5e-1)::BIGINT AS y, floor(z / 1e-1 + 5e-1)::BIGINT AS z FROM ({cloud})) WINDOW w AS (PARTITION BY frame_id ORDER BY id)")
    ap_sql = "WITH s AS (SELECT CASE c WHEN 0 THEN 'quality' ELSE 'toxic' END AS class, doc_id AS id, n_chars::DOUBLE AS score, CASE c WHEN 0 THEN quality = 1 ELSE toxic = 1 END AS positive FROM documents JOIN labels USING (doc_id), (VALUES (0), (1)) v(c)), r AS (SELECT *, row_number() OVER w AS rank, sum(positive::BIGINT) OVER (w ROWS UNBOUNDED PRECEDING) AS hits FROM s WINDOW w AS (PARTITION BY class ORDER BY score DESC, id)) SELECT class, round(avg(hits / rank), 6) AS ap, count(*) AS positives FROM r WHERE positive GROUP BY class"
    _add("average_precision", lambda s, p: measures.average_precision(detections(s, p)), ap_sql)
    _add("bpp_scene", lambda s, p: rate_table(s, p))


def detections(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = images.table(spark, sf_dir, "documents").select("doc_id", "n_chars").join(images.table(spark, sf_dir, "labels"), "doc_id")
    pair = lambda n: F.struct(F.lit(n).alias("class"), (F.col(n) == 1).alias("positive"))
    return d.select(F.col("doc_id").alias("id"), F.col("n_chars").cast("double").alias("score"), F.explode(F.array(pair("quality"), pair("toxic"))).alias("c")).select("c.class", "id", "score", "c.positive")


def rate_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits per point of the scene for each predictor and precision, byte-exact."""
    px, out = images.scene(spark, sf_dir), None
    for kind in ("none", "left", "three"):
        for d in (0.5, 0.1, 0.02):
            one = codec.bits_per_point(codec.encode(px, codec.CodecSpec(d, kind, (25, 240)))).select(F.lit(kind).alias("predictor"), F.lit(d).alias("d"), "bpp", "n_valid")
            out = one if out is None else out.unionByName(one)
    return out


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encode and decode the scene: pixels that come back, with their codes and ranges."""
    return codec.decode(codec.encode(images.scene(spark, sf_dir), codec.CodecSpec(0.1, "three")))


_register()


_ALL |= relational.QUERIES | workloads.QUERIES


def queries() -> dict:
    return {k: q for k, (q, _) in _ALL.items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for k, (_, s) in _ALL.items() if s}
