"""The experiments on the given tables, and queries for geometry, baselines, learned predictors, streams and sources.

QUERIES maps a name to (query, DuckDB SQL or None). Where a network or a compressed size is part of the answer there is no
SQL; round trips of such codecs are held against the quantised source."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import sql as sg
from .functions.storage import shared_dir, stored
from .operators import anchor, baselines, bytecodecs, codec, coders, geometry, learned, linear, measures
from .plans.relational import BEAMS, TURNS, calibration_of, coded, px, q
from .sources import container, images
from .sources.images import SQL, table
from .streaming import frames as streams

QUERIES: dict[str, tuple] = {}


def query(sql: str | None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = (f, sql)
        return f

    return keep


# Geometry

XYZ = f"xyz AS (SELECT frame_id, row * 240 + col AS id, hx * hs * range AS x, hy * hs * range AS y, dz * range AS z, range, row FROM ({SQL['scene']}) JOIN ({BEAMS}) USING (row) JOIN ({TURNS}) USING (col))"
CLOUD = "SELECT label::BIGINT AS frame_id, vec_id AS id, 60e0 * embedding[1]::DOUBLE AS x, 60e0 * embedding[2]::DOUBLE AS y, 60e0 * embedding[3]::DOUBLE AS z FROM embeddings"
COARSE = f"SELECT frame_id, id, floor(x / 1e0 + 5e-1) * 1e0 AS x, floor(y / 1e0 + 5e-1) * 1e0 AS y, floor(z / 1e0 + 5e-1) * 1e0 AS z FROM ({CLOUD})"
SQUARE = "(a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) + (a.z - b.z) * (a.z - b.z)"


def cloud_points(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "embeddings")
    return e.select(F.col("label").cast("long").alias("frame_id"), F.col("vec_id").alias("id"), *((F.lit(60.0) * F.col("embedding")[i].cast("double")).alias(c) for i, c in enumerate("xyz")))


def coarse_points(spark: SparkSession, sf: str) -> DataFrame:
    return cloud_points(spark, sf).select("frame_id", "id", *((F.floor(F.col(c) / F.lit(1.0) + F.lit(0.5)) * F.lit(1.0)).alias(c) for c in "xyz"))


def poses(spark: SparkSession, frames: int = 4) -> DataFrame:
    """The scene's sensor: one metre forward a frame, no turn."""
    return spark.range(frames).select(F.col("id").alias("frame_id"), F.array(*(F.lit(float(v)) for v in (1, 0, 0, 0, 1, 0, 0, 0, 1))).alias("rot"), F.array(F.col("id").cast("double"), F.lit(0.0), F.lit(0.0)).alias("t"))


def scene_cloud(spark: SparkSession, sf: str, placed: bool = False, d: float | None = None) -> DataFrame:
    """frame_id, id, x, y, z of the scene; d: of its decoded ranges."""
    img = images.scene(spark, sf)
    if d is not None:
        img = img.withColumn("range", linear.decode(linear.encode("range", d), d))
    at = geometry.unproject(img, *calibration_of(spark, sf), poses(spark) if placed else None)
    return at.select("frame_id", (F.col("row") * 240 + F.col("col")).cast("long").alias("id"), "x", "y", "z")


@query(f"WITH {XYZ} SELECT frame_id, id::BIGINT AS id, x + frame_id AS x, y, z FROM xyz")
def unproject_scene(spark: SparkSession, sf: str) -> DataFrame:
    return scene_cloud(spark, sf, placed=True)


@query(f"WITH {XYZ} SELECT frame_id, id::BIGINT AS id, round(atan2(y, x), 6) AS azimuth, round(asin(z / sqrt(x * x + y * y + z * z)), 6) AS elevation, round(sqrt(x * x + y * y + z * z), 6) AS range FROM xyz")
def project_spherical(spark: SparkSession, sf: str) -> DataFrame:
    """Global points back in the spherical coordinates of their frame's sensor."""
    back = geometry.project(scene_cloud(spark, sf, placed=True), poses(spark))
    return back.select("frame_id", "id", F.round("azimuth", 6).alias("azimuth"), F.round("elevation", 6).alias("elevation"), F.round("range", 6).alias("range"))


PSEUDO = f"pseudo AS (SELECT frame_id, greatest(0, least(15, floor((5e-1 - asin(z / r)) / (1e0 / 16))))::INT AS row, least(89, floor((atan2(y, x) + pi()) / (2 * pi() / 90)))::INT AS col, min(r) AS range FROM (SELECT *, sqrt(x * x + y * y + z * z) AS r FROM ({CLOUD})) WHERE r > 0 GROUP BY 1, 2, 3)"


def cloud_image(spark: SparkSession, sf: str) -> DataFrame:
    return geometry.pseudo_image(cloud_points(spark, sf), 16, 90, -0.5, 0.5)


@query(f"WITH {PSEUDO} SELECT frame_id, row, col, round(range, 6) AS range FROM pseudo")
def pseudo_image(spark: SparkSession, sf: str) -> DataFrame:
    return cloud_image(spark, sf).withColumn("range", F.round("range", 6))


@query(f"WITH {px('scene')} SELECT frame_id, row, col, frame_id::DOUBLE AS at_x FROM px")
def pose_attach(spark: SparkSession, sf: str) -> DataFrame:
    return geometry.attach_pose(images.scene(spark, sf), poses(spark), ["frame_id"]).select("frame_id", "row", "col", F.col("t")[0].alias("at_x"))


NEAREST = f"SELECT a.frame_id, a.id, min(sqrt({SQUARE})) AS dist FROM ({{}}) a JOIN ({{}}) b USING (frame_id) GROUP BY 1, 2"


@query(f"SELECT frame_id, id, round(dist, 6) AS dist FROM ({NEAREST.format(CLOUD, COARSE)})")
def nn_brute(spark: SparkSession, sf: str) -> DataFrame:
    """Reference by all pairs of a frame."""
    return geometry.brute(cloud_points(spark, sf), coarse_points(spark, sf)).groupBy("frame_id", "id").agg(F.round(F.sqrt(F.min("d2")), 6).alias("dist"))


@query(f"WITH {XYZ}, b AS (SELECT frame_id, id, x / range * c AS x, y / range * c AS y, z / range * c AS z FROM (SELECT *, floor(range / 1e-1 + 5e-1)::BIGINT * 1e-1 AS c FROM xyz)) SELECT frame_id, id::BIGINT AS id, round(dist, 5) AS dist FROM ({NEAREST.format('SELECT * FROM xyz WHERE row % 5 = 0', 'SELECT * FROM b')})")
def nn_aligned(spark: SparkSession, sf: str) -> DataFrame:
    """Points of every fifth beam and the nearest decoded point: one round, since a decoded pixel is at most d/2 away."""
    p = scene_cloud(spark, sf).where("id div 240 % 5 = 0")
    return geometry.nearest_aligned(p, scene_cloud(spark, sf, d=0.1), 0.0501).select("frame_id", "id", F.round("dist", 5).alias("dist"))


@query(f"SELECT frame_id, id, qid, rank, round(dist, 6) AS dist FROM (SELECT a.frame_id, a.id, b.id AS qid, sqrt({SQUARE}) AS dist, row_number() OVER (PARTITION BY a.frame_id, a.id ORDER BY {SQUARE}, b.id)::INT AS rank FROM ({CLOUD}) a JOIN ({CLOUD}) b USING (frame_id)) WHERE rank <= 4")
def knn_topk(spark: SparkSession, sf: str) -> DataFrame:
    p = cloud_points(spark, sf)
    return geometry.knn(p, p, 4, 6.0).select("frame_id", "id", "qid", "rank", F.round("dist", 6).alias("dist"))


@query(f"WITH k AS (SELECT a.frame_id, a.id, b.x, b.y, b.z FROM ({CLOUD}) a JOIN ({CLOUD}) b USING (frame_id) QUALIFY row_number() OVER (PARTITION BY a.frame_id, a.id ORDER BY {SQUARE}, b.id) <= 12) SELECT frame_id, id, count(*) AS n, round(avg(x), 5) AS mx, round(covar_pop(x, x), 4) AS cxx, round(covar_pop(x, y), 4) AS cxy, round(covar_pop(y, z), 4) AS cyz FROM k GROUP BY 1, 2")
def knn_moments(spark: SparkSession, sf: str) -> DataFrame:
    """Covariances of the twelve nearest points, which normals are read off."""
    p = cloud_points(spark, sf)
    m = geometry.moments(geometry.knn(p, p, 12, 12.0))
    return m.select("frame_id", "id", "n", F.round("mx", 5).alias("mx"), *(F.round(c, 4).alias(c) for c in ("cxx", "cxy", "cyz")))


@query(None)
def normals(spark: SparkSession, sf: str) -> DataFrame:
    return geometry.normals(cloud_points(spark, sf), 12.0)


@query(f"SELECT frame_id, round(max(dist), 6) AS r FROM (SELECT a.frame_id, a.id, min(sqrt({SQUARE})) AS dist FROM ({CLOUD}) a JOIN ({CLOUD}) b ON a.frame_id = b.frame_id AND a.id <> b.id GROUP BY 1, 2) GROUP BY 1")
def resolution(spark: SparkSession, sf: str) -> DataFrame:
    return measures.resolution(cloud_points(spark, sf), 6.0).withColumn("r", F.round("r", 6))


MATCH = f"SELECT a.frame_id, a.id, a.x, a.y, a.z, b.id AS qid, b.x AS qx, b.y AS qy, b.z AS qz FROM ({{}}) a JOIN ({{}}) b USING (frame_id) QUALIFY row_number() OVER (PARTITION BY a.frame_id, a.id ORDER BY {SQUARE}, b.id) = 1"


@query(f"WITH u AS ({MATCH.format(CLOUD, COARSE)}), v AS ({MATCH.format(COARSE, CLOUD)}), r AS (SELECT frame_id, max(dist) AS r FROM (SELECT a.frame_id, a.id, min(sqrt({SQUARE})) AS dist FROM ({CLOUD}) a JOIN ({CLOUD}) b ON a.frame_id = b.frame_id AND a.id <> b.id GROUP BY 1, 2) GROUP BY 1), m AS (SELECT frame_id, avg(pow((x - qx) * 6e-1 + (y - qy) * 8e-1, 2)) AS mse FROM u GROUP BY 1), k AS (SELECT frame_id, avg(pow((x - qx) * 6e-1 + (y - qy) * 8e-1, 2)) AS back FROM v GROUP BY 1) SELECT frame_id, round(r, 6) AS r, round(mse, 6) AS mse, round(back, 6) AS back, round(10 * log10(r * r / greatest(mse, back)), 5) AS psnr FROM r JOIN m USING (frame_id) JOIN k USING (frame_id)")
def psnr_given_normals(spark: SparkSession, sf: str) -> DataFrame:
    p = cloud_points(spark, sf).withColumns({"nx": F.lit(0.6), "ny": F.lit(0.8), "nz": F.lit(0.0)})
    return measures.psnr(p, coarse_points(spark, sf), 6.0)


@query(f"SELECT frame_id, floor(dist / 1e-1)::BIGINT AS bin, count(*) AS n FROM ({NEAREST.format(CLOUD, COARSE)}) GROUP BY 1, 2")
def error_map(spark: SparkSession, sf: str) -> DataFrame:
    return measures.error_map(cloud_points(spark, sf), coarse_points(spark, sf), 4.0, 0.1)


# Measures that need several runs


def h0(source: str, column: str = "delta") -> str:
    return f"(SELECT -sum(n / t * log2(n / t)) FROM (SELECT n, sum(n) OVER () AS t FROM (SELECT count(*) AS n FROM {source} GROUP BY {column})))"


def left_sql(image: str, d: float, name: str, channel: str = "range", block: int | None = None, more: str = "") -> str:
    part = "frame_id, row" + (f", col // {block}" if block else "")
    return f"{name} AS (SELECT code - coalesce(lag(code) OVER (PARTITION BY {part} ORDER BY col), 0) AS delta FROM (SELECT frame_id, row, col, floor({channel} / {d:e} + 5e-1)::BIGINT AS code FROM px{more}))"


PRECISIONS = (0.5, 0.2, 0.1, 0.05, 0.02)


def _rates(image: DataFrame, kinds, precisions=PRECISIONS) -> DataFrame:
    """method, d, bpp by order-0 entropy, err: one aggregation for each precision and predictor, the rows united."""
    out = None
    for d in precisions:
        c = linear.codes(image, d)
        err = image.agg(F.avg(F.abs(linear.decode(linear.encode("range", d), d) - F.col("range"))).alias("err"))
        for kind in kinds:
            one = measures.entropy_h0(linear.PREDICTORS[kind](c)).crossJoin(F.broadcast(err)).select(F.lit(kind).alias("method"), F.lit(d).alias("d"), F.round("h0", 5).alias("bpp"), F.round("err", 6).alias("err"))
            out = one if out is None else out.unionByName(one)
    return out


W1_SQL = "WITH " + px("scene") + ", " + ", ".join(left_sql("scene", d, f"l{i}") + f", c{i} AS (SELECT floor(range / {d:e} + 5e-1)::BIGINT AS delta FROM px)" for i, d in enumerate(PRECISIONS)) + " " + " UNION ALL ".join(f"SELECT '{m}' AS method, {d:e} AS d, round({h0(t + str(i))}, 5) AS bpp, (SELECT round(avg(abs(floor(range / {d:e} + 5e-1)::BIGINT * {d:e} - range)), 6) FROM px) AS err" for i, d in enumerate(PRECISIONS) for m, t in (("none", "c"), ("left", "l")))


@query(W1_SQL)
def w01_rate_distortion(spark: SparkSession, sf: str) -> DataFrame:
    """Rate against distortion of the scene: displacement along the ray for none and left at five precisions."""
    return _rates(images.scene(spark, sf), ("none", "left"))


@query(None)
def w01_codecs(spark: SparkSession, sf: str) -> DataFrame:
    """The same with byte-exact rates and symmetric Chamfer distance, point codecs beside image codecs."""
    img, out = images.scene(spark, sf), None
    cloud = stored(scene_cloud(spark, sf), "w01-cloud")
    for d in (0.5, 0.1, 0.02):
        back = scene_cloud(spark, sf, d=d)
        near = geometry.nearest_aligned(cloud, back, d * 0.501).agg(F.round(F.avg("dist"), 6).alias("cd"))
        for kind in ("none", "left", "three"):
            bits = codec.bits_per_point(codec.encode(img, codec.CodecSpec(d, kind)))
            one = bits.crossJoin(F.broadcast(near)).select(F.lit(kind).alias("method"), F.lit(d).alias("d"), "bpp", "cd")
            out = one if out is None else out.unionByName(one)
        png = bytecodecs.encode_images(bytecodecs.images_of(img, 1 / d), "png16").agg(F.round(F.sum("bits") / F.sum("n"), 6).alias("bpp")).crossJoin(F.broadcast(near))
        out = out.unionByName(png.select(F.lit("png16").alias("method"), F.lit(d).alias("d"), "bpp", "cd"))
    for depth in (8, 10, 12):
        side = 160.0 / (1 << depth)
        got = bytecodecs.encode_points(bytecodecs.frames_of(cloud, side, 80.0 - side / 2), "octree", depth).agg(F.sum("bits").alias("bits")).crossJoin(F.broadcast(cloud.agg(F.count(F.lit(1)).alias("n"))))
        cells = [((F.floor((F.col(c) + F.lit(80.0)) / F.lit(side)) + F.lit(0.5)) * F.lit(side) - F.lit(80.0)).alias(c) for c in "xyz"]
        near = geometry.nearest_aligned(cloud, cloud.select("frame_id", "id", *cells), side).agg(F.round(F.avg("dist"), 6).alias("cd"))
        out = out.unionByName(got.crossJoin(F.broadcast(near)).select(F.lit("octree").alias("method"), F.lit(side).alias("d"), F.round(F.col("bits") / F.col("n"), 6).alias("bpp"), "cd"))
    return out


@query(None)
def w02_psnr(spark: SparkSession, sf: str) -> DataFrame:
    """Point-to-plane PSNR of the first frame's decoded points at three precisions; normals once, from twelve neighbours."""
    p = scene_cloud(spark, sf).where("frame_id = 0")
    n = stored(p.join(geometry.normals(p, 2.0), ["frame_id", "id"]), "w02-normals")
    out = None
    for d in (0.5, 0.1):
        one = measures.psnr(n, scene_cloud(spark, sf, d=d).where("frame_id = 0"), 1.0).select(F.lit(d).alias("d"), "frame_id", "psnr")
        out = one if out is None else out.unionByName(one)
    return out


W3_SQL = f"WITH {PSEUDO}, px AS (SELECT * FROM pseudo), {left_sql('', 0.1, 'z')} SELECT 'left' AS method, round({h0('z')}, 4) AS bpp, (SELECT count(*) FROM px) AS n_valid"


@query(W3_SQL)
def w03_bare_cloud(spark: SparkSession, sf: str) -> DataFrame:
    """A cloud without poses becomes a pseudo image, which the intra-frame codec compresses."""
    return measures.entropy_h0(linear.delta_left(linear.codes(cloud_image(spark, sf), 0.1))).select(F.lit("left").alias("method"), F.round("h0", 4).alias("bpp"), "n_valid")


DOT = "list_aggregate(list_transform(list_zip(v.e, c.e), p -> p[1] * p[2]), 'sum')"


@query("WITH s AS (SELECT CASE c WHEN 0 THEN 'quality' ELSE 'toxic' END AS class, doc_id AS id, floor(n_chars / 25e0 + 5e-1)::BIGINT * 25e0 AS score, CASE c WHEN 0 THEN quality = 1 ELSE toxic = 1 END AS positive FROM documents JOIN labels USING (doc_id), (VALUES (0), (1)) v(c)), r AS (SELECT *, row_number() OVER w AS rank, sum(positive::BIGINT) OVER (w ROWS UNBOUNDED PRECEDING) AS hits FROM s WINDOW w AS (PARTITION BY class ORDER BY score DESC, id)) SELECT class, round(avg(hits / rank), 6) AS ap, count(*) AS positives FROM r WHERE positive GROUP BY class")
def w04_downstream(spark: SparkSession, sf: str) -> DataFrame:
    """A detector's score on decoded input: two classes ranked by a feature that went through the quantiser."""
    d = table(spark, sf, "documents").select("doc_id", "n_chars").join(table(spark, sf, "labels"), "doc_id")
    pair = lambda n: F.struct(F.lit(n).alias("class"), (F.col(n) == 1).alias("positive"))
    score = linear.decode(linear.encode(F.col("n_chars").cast("double"), 25.0), 25.0)
    s = d.select(F.col("doc_id").alias("id"), score.alias("score"), F.explode(F.array(pair("quality"), pair("toxic"))).alias("c")).select("c.class", "id", "score", "c.positive")
    return measures.precision_curve(s)


@query("WITH s AS (SELECT CASE c WHEN 0 THEN 'quality' ELSE 'toxic' END AS class, doc_id AS id, n_chars::DOUBLE AS score, CASE c WHEN 0 THEN quality = 1 ELSE toxic = 1 END AS positive FROM documents JOIN labels USING (doc_id), (VALUES (0), (1)) v(c)), r AS (SELECT *, row_number() OVER w AS rank, sum(positive::BIGINT) OVER (w ROWS UNBOUNDED PRECEDING) AS hits FROM s WINDOW w AS (PARTITION BY class ORDER BY score DESC, id)) SELECT round(avg(ap), 6) AS map, count(*) AS classes FROM (SELECT class, round(avg(hits / rank), 6) AS ap FROM r WHERE positive GROUP BY class)")
def mean_ap(spark: SparkSession, sf: str) -> DataFrame:
    d = table(spark, sf, "documents").select("doc_id", "n_chars").join(table(spark, sf, "labels"), "doc_id")
    pair = lambda n: F.struct(F.lit(n).alias("class"), (F.col(n) == 1).alias("positive"))
    return measures.mean_ap(d.select(F.col("doc_id").alias("id"), F.col("n_chars").cast("double").alias("score"), F.explode(F.array(pair("quality"), pair("toxic"))).alias("c")).select("c.class", "id", "score", "c.positive"))


def _accuracy_sql(image: str, kinds) -> str:
    made = {"none": "code", "left": "code - coalesce(lag(code) OVER (PARTITION BY frame_id, row ORDER BY col), 0)"}
    return " UNION ALL ".join(f"SELECT '{image}' AS image, '{k}' AS predictor, accuracy, n_valid FROM (WITH {px(image)}, {coded(image)}, z AS (SELECT {made[k]} AS delta FROM q) SELECT round(100 * sum((delta = 0)::BIGINT) / count(*), 6) AS accuracy, count(*) AS n_valid FROM z)" for k in kinds)


@query(" UNION ALL ".join(_accuracy_sql(i, ("none", "left")) for i in ("scene", "part", "lineitem")))
def w05_accuracy(spark: SparkSession, sf: str) -> DataFrame:
    """Accuracy at 0.1 m by image and predictor."""
    out = None
    for i in ("scene", "part", "lineitem"):
        for k in ("none", "left"):
            one = measures.accuracy(linear.PREDICTORS[k](q(spark, sf, i))).select(F.lit(i).alias("image"), F.lit(k).alias("predictor"), "accuracy", "n_valid")
            out = one if out is None else out.unionByName(one)
    return out


# Learned predictors: trained on frames 4 and later of the scene, measured on frames 0 to 3.

SMALL = {"context": (4, 5), "width": 0.2}
TRAIN = {"steps": 150, "rate": 5e-3, "milestones": (110, 140), "batch_size": 64}
SPEC = codec.CodecSpec(0.1, "learned", (25, 240), gop=4)


def angles(columns: int = 240, beams: int = 25) -> tuple[np.ndarray, np.ndarray]:
    """Azimuths and elevations of the scene's sensor in radians."""
    c, r = np.arange(columns), np.arange(beams)
    ta, te = 2 * (c % 60 + 0.5) / 60 - 1, 0.04 - 0.26 * r * r / 576
    return 2 * np.arctan(ta) + (c // 60) * np.pi / 2, 2 * np.arctan(te)


def sensor(columns: int = 240, beams: int = 25) -> codec.Sensor:
    c, r = np.arange(columns), np.arange(beams)
    ta, te = 2 * (c % 60 + 0.5) / 60 - 1, 0.04 - 0.26 * r * r / 576
    ux, uy, hs, dz = (1 - ta * ta) / (1 + ta * ta), 2 * ta / (1 + ta * ta), (1 - te * te) / (1 + te * te), 2 * te / (1 + te * te)
    quarter = c // 60
    hx, hy = np.choose(quarter, [ux, -uy, -ux, uy]), np.choose(quarter, [uy, ux, -uy, -ux])
    return codec.Sensor(np.stack([hs[:, None] * hx, hs[:, None] * hy, np.repeat(dz[:, None], columns, 1)], 2))


def spec_of(**changes) -> anchor.NetSpec:
    return anchor.spec_for(anchor.NetSpec(**(SMALL | changes)), *angles())


_NETS: dict = {}  # frozen networks of this process, by application, table and spec


def trained(spark: SparkSession, sf: str, spec: anchor.NetSpec, mixed: bool = False, d: float = 0.1, seed: int = 0, steps: int = TRAIN["steps"]) -> anchor.Net:
    key = (spark.sparkContext.applicationId, sf, spec, mixed, d, seed, steps)
    if key not in _NETS:
        train = images.scene(spark, sf, frames=12).where("frame_id >= 4")
        net, _ = learned.train(train, spec, codec.CodecSpec(d, "learned", (25, 240), gop=4), steps, every=7, sensor=sensor() if spec.temporal == "knn" else None, mixed=mixed, rate=TRAIN["rate"], milestones=TRAIN["milestones"], batch_size=TRAIN["batch_size"], seed=seed, most=6_000)
        _NETS[key] = net.freeze().dumps()
    return anchor.Net.loads(_NETS[key])


def accuracy_of(spark: SparkSession, sf: str, spec: anchor.NetSpec, **options) -> DataFrame:
    net, img = trained(spark, sf, spec, **options), images.scene(spark, sf)
    got = codec.deltas(img, SPEC, net) if spec.temporal == "none" else codec.deltas_temporal(img, SPEC, net, sensor())
    return measures.accuracy(got)


def _table(rows: list[tuple[str, DataFrame]], name: str) -> DataFrame:
    out = None
    for n, one in rows:
        one = one.withColumn(name, F.lit(n))
        out = one if out is None else out.unionByName(one)
    return out


@query(None)
def w05_learned(spark: SparkSession, sf: str) -> DataFrame:
    """Accuracy of the anchor network and of the convolutional one beside the linear predictors, same context."""
    c = q(spark, sf, "scene")
    rows = [(k, measures.accuracy(linear.PREDICTORS[k](c))) for k in ("left", "three")]
    rows += [("cnn", accuracy_of(spark, sf, spec_of(head="cnn", width=0.1))), ("anchor", accuracy_of(spark, sf, spec_of()))]
    return _table(rows, "predictor")


@query(None)
def w06_losses(spark: SparkSession, sf: str) -> DataFrame:
    return _table([(k, accuracy_of(spark, sf, spec_of(head=k))) for k in ("mse", "mae", "multibin", "anchor")], "loss")


@query(None)
def w07_temporal(spark: SparkSession, sf: str) -> DataFrame:
    """No previous frame, its pixels of the same rows and columns, its nearest points; and the non-learned previous pixel."""
    rows = [("previous pixel", measures.accuracy(linear.delta_prev_frame(q(spark, sf, "scene"), gop=4)))]
    return _table(rows + [(k, accuracy_of(spark, sf, spec_of(temporal=k, points=8))) for k in ("none", "image", "knn")], "temporal")


@query(None)
def w09_context(spark: SparkSession, sf: str) -> DataFrame:
    """Context shapes (tall, wide, small, square) and offsets instead of angles."""
    shapes = {"5x1 angles": {"context": (5, 1)}, "1x5 angles": {"context": (1, 5)}, "3x5 indices": {"context": (3, 5), "angles": False}, "3x5 angles": {"context": (3, 5)}, "4x5 angles": {}}
    return _table([(n, accuracy_of(spark, sf, spec_of(**c))) for n, c in shapes.items()], "context")


@query(None)
def w18_precision_strategy(spark: SparkSession, sf: str) -> DataFrame:
    """One network trained on mixed precisions against networks trained on one each; entropy at both."""
    rows = []
    for d in (0.1, 0.02):
        for name, mixed in (("fixed", False), ("mixed", True)):
            net = trained(spark, sf, spec_of(), mixed=mixed, d=d if not mixed else 0.1)
            spec = codec.CodecSpec(d, "learned", (25, 240))
            rows.append((name, measures.entropy_h0(codec.deltas(images.scene(spark, sf), spec, net)).withColumn("d", F.lit(d))))
    return _table(rows, "strategy")


SOURCE = f"WITH {px('scene')}, {coded('scene')} SELECT * FROM q"


def _round_trip(spark, sf, spec, blocks=(25, 60)):
    net, img = trained(spark, sf, spec), images.scene(spark, sf)
    if spec.temporal == "none":
        how = codec.CodecSpec(0.1, "learned", blocks)
        return codec.decode(codec.encode(img, how, net), net).select("frame_id", "row", "col", "code")
    how = codec.CodecSpec(0.1, "learned", (25, 240), gop=4)
    return codec.decode_temporal(codec.encode_temporal(img, how, net, sensor()), how, net, sensor()).select("frame_id", "row", "col", "code")


@query(SOURCE)
def codec_roundtrip_anchor(spark: SparkSession, sf: str) -> DataFrame:
    """Encode and decode the scene with the anchor network: the quantised source comes back bit by bit."""
    return _round_trip(spark, sf, spec_of())


@query(SOURCE)
def codec_roundtrip_cnn(spark: SparkSession, sf: str) -> DataFrame:
    return _round_trip(spark, sf, spec_of(head="cnn", width=0.1))


@query(SOURCE)
def codec_roundtrip_anchor_t_image(spark: SparkSession, sf: str) -> DataFrame:
    return _round_trip(spark, sf, spec_of(temporal="image", points=8))


@query(SOURCE)
def codec_roundtrip_anchor_t_knn(spark: SparkSession, sf: str) -> DataFrame:
    return _round_trip(spark, sf, spec_of(temporal="knn", points=8))


@query(None)
def anchor_rate(spark: SparkSession, sf: str) -> DataFrame:
    """Byte-exact rate of the anchor codec beside the linear ones."""
    img, net = images.scene(spark, sf), trained(spark, sf, spec_of())
    rows = [(k, codec.bits_per_point(codec.encode(img, codec.CodecSpec(0.1, k, (25, 240))))) for k in ("none", "left", "three")]
    return _table(rows + [("anchor", codec.bits_per_point(codec.encode(img, SPEC, net)))], "predictor")


@query(f"WITH {px('lineitem')} " + " UNION ALL ".join(f"SELECT '{c}' AS channel, frame_id, row, col, floor({c} / {d:e} + 5e-1)::BIGINT AS code FROM px" for c, d in (("range", 0.02), ("intensity", 0.1), ("elongation", 0.1))))
def codec_roundtrip_multi(spark: SparkSession, sf: str) -> DataFrame:
    """Three channels, each with a precision of its own, through one container."""
    got, precision = None, {"range": 0.02, "intensity": 0.1, "elongation": 0.1}
    for name, one in channels(images.lineitem_img(spark, sf), precision).items():
        back = codec.decode(one).select(F.lit(name).alias("channel"), "frame_id", "row", "col", "code")
        got = back if got is None else got.unionByName(back)
    return got


def channels(img: DataFrame, precision: dict[str, float], predictor: str = "three", block: tuple[int, int] = (16, 50)) -> dict[str, DataFrame]:
    """Container rows of every channel of an image: attributes are coded like ranges, each with its own precision."""
    return {c: codec.encode(img.select("frame_id", "row", "col", F.col(c).alias("range")), codec.CodecSpec(d, predictor, block)) for c, d in precision.items()}


# Coders, blocks, beams, attributes


@query(None)
def w08_coders(spark: SparkSession, sf: str) -> DataFrame:
    """Bits per point of every coder at two precisions, on the three-neighbour residuals of whole frames."""
    rows = []
    for d in (0.1, 0.02):
        for name in ("sparse_arith", "sparse_rowcol", "rle_lzma", "varint_lzma", "huffman", "arith", "arith_ctx", "deflate"):
            rows.append((name, codec.bits_per_point(codec.encode(images.scene(spark, sf), codec.CodecSpec(d, "three", (25, 240), name)), include_mask=False).withColumn("d", F.lit(d))))
    return _table(rows, "coder")


@query(" UNION ALL ".join(f"SELECT {d:e} AS d, n_valid, nonzero, runs, h0 FROM (WITH {px('scene')}, z AS (SELECT frame_id, row, col, code - coalesce(lag(code) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS delta FROM (SELECT frame_id, row, col, floor(range / {d:e} + 5e-1)::BIGINT AS code FROM px)), g AS (SELECT delta, delta IS DISTINCT FROM lag(delta) OVER (PARTITION BY frame_id, row ORDER BY col) AS new FROM z) SELECT count(*) AS n_valid, sum((delta <> 0)::BIGINT)::BIGINT AS nonzero, sum(new::BIGINT)::BIGINT AS runs, round({h0('z')}, 5) AS h0 FROM g)" for d in (0.1, 0.02)))
def w08_models(spark: SparkSession, sf: str) -> DataFrame:
    """What the coders' sizes follow: residuals that are not zero, runs, order-0 entropy."""
    from pyspark.sql import Window

    out, w = None, Window.partitionBy("frame_id", "row").orderBy("col")
    for d in (0.1, 0.02):
        z = linear.delta_left(q(spark, sf, "scene", d))
        g = z.withColumn("new", ~F.col("delta").eqNullSafe(F.lag("delta").over(w)))
        one = g.agg(F.count(F.lit(1)).alias("n_valid"), F.sum((F.col("delta") != 0).cast("long")).alias("nonzero"), F.sum(F.col("new").cast("long")).alias("runs"))
        one = one.crossJoin(F.broadcast(measures.entropy_h0(z).select(F.round("h0", 5).alias("h0")))).withColumn("d", F.lit(d))
        out = one if out is None else out.unionByName(one)
    return out


@query(None)
def w10_latency(spark: SparkSession, sf: str) -> DataFrame:
    """Wall milliseconds a frame of encoding and decoding the lineitem image, by predictor."""
    img = stored(images.lineitem_img(spark, sf), "w10-image")
    n, rows = max(1, img.select("frame_id").distinct().count()), []
    for kind in ("left", "three"):
        at = time.time()
        done = stored(codec.encode(img, codec.CodecSpec(0.1, kind)), "w10-coded")
        mid = time.time()
        codec.decode(done).write.format("noop").mode("overwrite").save()
        rows.append((kind, 1000 * (mid - at) / n, 1000 * (time.time() - mid) / n))
    return spark.createDataFrame(rows, "method string, encode_ms double, decode_ms double")


@query(None)
def w11_breakdown(spark: SparkSession, sf: str) -> DataFrame:
    """Milliseconds a frame of grouping into blocks, prediction and entropy coding."""
    img, spec = stored(images.lineitem_img(spark, sf), "w11-image"), codec.CodecSpec(0.1, "three")
    n, rows, before = max(1, img.select("frame_id").distinct().count()), [], 0.0
    for name, df in (("blocks", codec.to_blocks(img, spec)), ("prediction", codec.deltas(img, spec)), ("entropy", codec.encode(img, spec))):
        at = time.time()
        df.write.format("noop").mode("overwrite").save()
        took = time.time() - at
        rows.append((name, 1000 * max(0.0, took - before) / n))
        before = took
    return spark.createDataFrame(rows, "stage string, ms double")


BLOCKS = ((25, 240, "whole"), (5, 24, "5x24"), (5, 12, "5x12"), (5, 13, "5x13"))


@query(f"WITH {px('scene')}, " + ", ".join(left_sql("scene", 0.1, f"b{i}", block=w) for i, (_, w, _) in enumerate(BLOCKS)) + f", r AS ({' UNION ALL '.join(f'SELECT {chr(39)}{n}{chr(39)} AS block, {h0(f'b{i}')} AS h' for i, (_, _, n) in enumerate(BLOCKS))}) SELECT block, round(h, 5) AS bpp, round(100 * (h / (SELECT h FROM r WHERE block = 'whole') - 1), 3) AS penalty FROM r")
def w12_block_penalty(spark: SparkSession, sf: str) -> DataFrame:
    """Rate of independent blocks against whole frames, left predictor: prediction starts anew in every block."""
    c, out = q(spark, sf, "scene"), None
    for h, w, name in BLOCKS:
        one = measures.entropy_raw(linear.delta_left(c, block=(h, w))).select(F.lit(name).alias("block"), "h")
        out = one if out is None else out.unionByName(one)
    whole = out.where("block = 'whole'").select(F.col("h").alias("_w"))
    return out.crossJoin(F.broadcast(whole)).select("block", F.round("h", 5).alias("bpp"), F.round(100 * (F.col("h") / F.col("_w") - 1), 3).alias("penalty"))


@query(f"WITH {px('scene')}, {left_sql('scene', 0.1, 'a')}, {left_sql('scene', 0.1, 'b', more=' WHERE row % 2 = 0')} SELECT 25 AS beams, round({h0('a')}, 5) AS bpp UNION ALL SELECT 13, round({h0('b')}, 5)")
def w13_half_the_beams(spark: SparkSession, sf: str) -> DataFrame:
    img, out = images.scene(spark, sf), None
    for n, some in ((25, img), (13, images.subsample_rows(img))):
        one = measures.entropy_h0(linear.delta_left(linear.codes(some, 0.1))).select(F.lit(n).alias("beams"), F.round("h0", 5).alias("bpp"))
        out = one if out is None else out.unionByName(one)
    return out


@query(None)
def w14_fieldwise(spark: SparkSession, sf: str) -> DataFrame:
    """A point-file codec on the scene's coordinates against the image codec at the same precision."""
    img, cloud = images.scene(spark, sf), scene_cloud(spark, sf)
    points = bytecodecs.encode_points(bytecodecs.frames_of(cloud, 0.1), "fieldwise", 0).agg(F.round(F.sum("bits") / F.sum("n"), 6).alias("bpp"))
    image = codec.bits_per_point(codec.encode(img, codec.CodecSpec(0.1, "three"))).select("bpp")
    return _table([("fieldwise", points), ("three", image)], "method")


CHOICES = ((0.1, 0.1, 0.1), (0.02, 0.1, 0.1), (0.1, 0.02, 0.02), (0.02, 0.02, 0.02), (0.5, 0.5, 0.5))


def _w15_sql() -> str:
    parts, names = [], ("range", "intensity", "elongation")
    for i, choice in enumerate(CHOICES):
        parts += [left_sql("lineitem", d, f"z{i}{c[0]}", c) for c, d in zip(names, choice)]
    rows = " UNION ALL ".join(f"SELECT {i} AS choice, '{c}' AS channel, {d:e} AS d, round({h0(f'z{i}{c[0]}')}, 4) AS bpp" for i, choice in enumerate(CHOICES) for c, d in zip(names, choice))
    return f"WITH {px('lineitem')}, {', '.join(parts)} {rows}"


@query(_w15_sql())
def w15_attributes(spark: SparkSession, sf: str) -> DataFrame:
    """Rates of range, intensity and elongation under five choices of precisions."""
    img, out = images.lineitem_img(spark, sf), None
    for i, choice in enumerate(CHOICES):
        for c, d in zip(("range", "intensity", "elongation"), choice):
            z = linear.delta_left(linear.codes(img.select("frame_id", "row", "col", F.col(c).alias("range")), d))
            one = measures.entropy_h0(z).select(F.lit(i).alias("choice"), F.lit(c).alias("channel"), F.lit(d).alias("d"), F.round("h0", 4).alias("bpp"))
            out = one if out is None else out.unionByName(one)
    return out


@query(None)
def bpp_by_channel(spark: SparkSession, sf: str) -> DataFrame:
    """Bytes of every channel and of all (channel null): a rollup over the container."""
    got = None
    for name, one in channels(images.lineitem_img(spark, sf), {"range": 0.02, "intensity": 0.1, "elongation": 0.1}).items():
        one = one.select(F.lit(name).alias("channel"), "bits", "n_valid")
        got = one if got is None else got.unionByName(one)
    return got.rollup("channel").agg(F.sum("bits").alias("bits"), F.round(F.sum("bits") / F.max("n_valid"), 3).alias("scale"))


W16 = [(i, d) for i in ("scene", "lineitem") for d in (0.02, 0.1, 0.2)]


@query(" UNION ALL ".join(f"SELECT '{i}' AS image, {d:e} AS d, delta, n FROM (WITH {px(i)}, {left_sql(i, d, 'z')} SELECT greatest(-20, least(20, delta))::BIGINT AS delta, count(*) AS n FROM z GROUP BY 1)" for i, d in W16))
def w16_residuals(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for i, d in W16:
        one = measures.residual_histogram(linear.delta_left(q(spark, sf, i, d))).select(F.lit(i).alias("image"), F.lit(d).alias("d"), "delta", "n")
        out = one if out is None else out.unionByName(one)
    return out


@query(None)
def w17_autoencoder(spark: SparkSession, sf: str) -> DataFrame:
    """Patch auto-encoder (principal components): its largest error has no bound, unlike the quantiser's."""
    patch, rows = stored(bytecodecs.patches(images.scene(spark, sf), 5), "w17-patches"), []
    for k in (1, 4, 12):
        mean, basis = bytecodecs.components(patch, k)
        got = bytecodecs.autoencode(patch, mean, basis, 0.5).join(patch, ["frame_id", "block_row", "block_col"])
        err = got.select(F.explode(F.zip_with("v", "back", lambda a, b: F.abs(a - b))).alias("e")).agg(F.round(F.avg("e"), 4).alias("mean_error"), F.round(F.max("e"), 4).alias("max_error"))
        rate = measures.entropy_h0(got.select(F.posexplode("codes").alias("i", "delta")).select("delta")).select(F.round(F.col("h0") * k / 25, 5).alias("bpp"))
        rows.append((f"components {k}", err.crossJoin(F.broadcast(rate))))
    return _table(rows, "method")


@query(f"SELECT floor(dist / 1e-1)::BIGINT AS bin, count(*) AS n FROM ({NEAREST.format(CLOUD, COARSE)}) GROUP BY 1")
def w19_error_bins(spark: SparkSession, sf: str) -> DataFrame:
    return error_map(spark, sf).groupBy("bin").agg(F.sum("n").alias("n"))


@query(" UNION ALL ".join(f"SELECT '{i}' AS image, count(*) AS points, (count(*) * 32)::BIGINT AS image_bits, (count(*) * 96)::BIGINT AS cloud_bits FROM ({SQL[i]})" for i in ("scene", "part", "lineitem", "events", "embedding", "orders", "conversation")))
def w20_raw_rates(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for i in ("scene", "part", "lineitem", "events", "embedding", "orders", "conversation"):
        one = images.IMAGES[i](spark, sf).agg(F.count(F.lit(1)).alias("points")).select(F.lit(i).alias("image"), "points", (F.col("points") * 32).alias("image_bits"), (F.col("points") * 96).alias("cloud_bits"))
        out = one if out is None else out.unionByName(one)
    return out


@query(f"WITH {px('scene')}, {left_sql('scene', 0.1, 'z')}, c AS (SELECT floor(range / 1e-1 + 5e-1)::BIGINT AS delta FROM px) SELECT round({h0('c')}, 4) AS none, round({h0('z')}, 4) AS \"left\", round(100 * (1 - {h0('z')} / {h0('c')}), 2) AS saved")
def rd_compare(spark: SparkSession, sf: str) -> DataFrame:
    """Rates of two methods where both distort by as much, and what the second saves in percent."""
    curves = _rates(images.scene(spark, sf), ("none", "left"), (0.2, 0.1, 0.05)).select("method", F.col("err").alias("distortion"), "bpp")
    curves = stored(curves, "curves")
    at = curves.orderBy("distortion").collect()[2].distortion  # the middle precision's
    both = measures.rd_compare(curves, at).groupBy().pivot("method", ["none", "left"]).agg(F.first("bpp"))
    return both.select(F.round("none", 4).alias("none"), F.round("left", 4).alias("left"), F.round(100 * (1 - F.col("left") / F.col("none")), 2).alias("saved"))


@query(None)
def tune_precision(spark: SparkSession, sf: str) -> DataFrame:
    """Rate control: the coarsest precision that keeps the scene's rate at 3 bits per point or below, by bisection over frames of one in two."""
    d, rate = tuned(images.scene(spark, sf).where("frame_id % 2 = 0"), 3.0)
    return spark.createDataFrame([(d, rate)], "d double, bpp double")


def tuned(sample: DataFrame, target: float, low: float = 1e-4, high: float = 0.5, passes: int = 8) -> tuple[float, float]:
    """(precision, bits per point): the finest precision between low and high whose rate is at most target, as `passes` halvings find it."""
    sample = stored(sample, "rate-sample")
    rate = lambda d: codec.bits_per_point(codec.encode(sample, codec.CodecSpec(d, "three"))).first().bpp
    best = (high, rate(high))
    for _ in range(passes):
        mid = (low * high) ** 0.5
        got = rate(mid)
        if got <= target:
            high, best = mid, (mid, got)
        else:
            low = mid
    return best


# Baseline byte codecs

CELLS = f"SELECT DISTINCT frame_id, x, y, z FROM (SELECT frame_id, floor((x + 64e0) / 1e0 + 5e-1)::BIGINT AS x, floor((y + 64e0) / 1e0 + 5e-1)::BIGINT AS y, floor((z + 64e0) / 1e0 + 5e-1)::BIGINT AS z FROM ({CLOUD}))"


def _points(method: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        rows = bytecodecs.frames_of(cloud_points(spark, sf), 1.0, 64.0)
        return bytecodecs.decode_points(bytecodecs.encode_points(rows, method, 8), method, 8)

    return run


for _method, _name in (("octree", "octree_roundtrip"), ("octree_none", "octree_roundtrip_order0"), ("octree_level", "octree_nn_roundtrip")):
    QUERIES[_name] = (_points(_method), CELLS)
for _method in ("kdtree", "fieldwise"):
    QUERIES[f"{_method}_roundtrip"] = (_points(_method), CELLS.replace("DISTINCT ", ""))

SIXTEEN = f"WITH {px('scene')} SELECT frame_id, row, col, greatest(1, least(65535, floor(range * 1e2 + 5e-1)))::BIGINT AS v FROM px"


def _pictures(method: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        img = images.scene(spark, sf, label=True)
        ground = bytecodecs.ground_rows(img, 100.0) if method == "cluster" else None
        return bytecodecs.decode_images(bytecodecs.encode_images(bytecodecs.images_of(img, 100.0), method, ground), method, ground)

    return run


for _method, _name in (("png16", "png16_roundtrip"), ("video", "video_roundtrip_sur"), ("cluster", "cluster_roundtrip_sur")):
    QUERIES[_name] = (_pictures(_method), SIXTEEN)


@query(f"WITH {XYZ}, h AS (SELECT sum(-range / (z / range)) / sum(1 / ((z / range) * (z / range))) AS h FROM xyz WHERE z < 0) SELECT round(h, 5) AS height FROM h")
def ground_plane_fit(spark: SparkSession, sf: str) -> DataFrame:
    """Height of the ground below the sensor: least squares over the rays that look down."""
    at = geometry.unproject(images.scene(spark, sf), *calibration_of(spark, sf)).withColumn("dz", F.col("z") / F.col("range")).where("z < 0")
    return at.agg(F.round(F.sum(-F.col("range") / F.col("dz")) / F.sum(1 / (F.col("dz") * F.col("dz"))), 5).alias("height"))


@query(None)
def dct8_sur(spark: SparkSession, sf: str) -> DataFrame:
    """Transform coding of the 16-bit image: rate and largest error, which is not bounded by the step."""
    def run(batches):
        import pyarrow as pa

        for b in batches:
            for x in b.to_pylist():
                v = bytecodecs._image(x)
                back, raw = bytecodecs.dct8(v, 40.0)
                yield pa.RecordBatch.from_arrays([pa.array([x["frame_id"]]), pa.array([len(x["r"])], pa.int64()), pa.array([8 * len(raw)], pa.int64()), pa.array([float(np.abs(back - v)[v > 0].max())])], ["frame_id", "n", "bits", "worst"])

    return bytecodecs.images_of(images.scene(spark, sf), 100.0).mapInArrow(run, "frame_id long, n long, bits long, worst double")


LEAVES = "l6 AS (SELECT DISTINCT frame_id, (" + " | ".join(f"(((greatest(0, least(63, floor(({c} + 64e0) / 2e0)))::BIGINT >> {i}) & 1) << {3 * i + k})" for k, c in enumerate("xyz") for i in range(6)) + f") AS key FROM ({CLOUD}))"
UP = ", ".join(f"l{n} AS (SELECT frame_id, key >> 3 AS key, bit_or((1 << (key & 7))::BIGINT) AS byte FROM l{n + 1} GROUP BY 1, 2)" for n in range(5, -1, -1))
NODES = "nodes AS (" + " UNION ALL ".join(f"SELECT frame_id, {n} AS level, key, byte FROM l{n}" for n in range(6)) + ")"
CONTEXT = "c AS (SELECT byte, ctx, count(*) AS n FROM ({}) GROUP BY 1, 2), t AS (SELECT ctx, n, sum(n) OVER (PARTITION BY ctx) AS t FROM c), e AS (SELECT ctx, sum(n) AS n, round(-sum(n / t * log2(n / t)), 6) AS h FROM t GROUP BY ctx) SELECT round(sum(h * n) / sum(n), 5) AS h_ctx, sum(n)::BIGINT AS nodes FROM e"


def _nodes(spark, sf):
    return baselines.octree_occupancy(baselines.voxels(cloud_points(spark, sf), 6, 128.0), 6)


@query(f"WITH {LEAVES}, {UP}, {NODES}, h AS (SELECT {h0('nodes', 'byte')} AS h, (SELECT count(*) FROM nodes) AS n) SELECT round(round(h, 6) * n / 500, 5) AS bpp, n AS nodes FROM h")
def octree_entropy(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.octree_entropy(_nodes(spark, sf), 500)


@query(f"WITH {LEAVES}, {UP}, {NODES}, {CONTEXT.format('SELECT a.byte, coalesce(bit_count(b.byte), 0) AS ctx FROM nodes a LEFT JOIN nodes b ON b.frame_id = a.frame_id AND b.level = a.level - 1 AND b.key = a.key >> 3')}")
def octree_entropy_ctx(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.octree_entropy_ctx(_nodes(spark, sf))


@query(f"WITH {LEAVES}, {UP}, {NODES}, {CONTEXT.format('SELECT a.byte, coalesce(bit_count(b.byte), 0) AS ctx FROM nodes a LEFT JOIN nodes b ON b.frame_id = a.frame_id - 1 AND b.level = a.level AND b.key = a.key')}")
def octree_prev_ctx(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.octree_prev_ctx(_nodes(spark, sf))


# Coders on texts, linear predictors' variants


@query("SELECT item_id, text, octet_length(encode(text))::INT AS n FROM benchmark")
def coder_bytes_documents(spark: SparkSession, sf: str) -> DataFrame:
    """Bytes of texts as symbols through the arithmetic coder and back."""
    def run(batches):
        import pyarrow as pa

        for b in batches:
            raw = [t.encode() for t in b.column("text").to_pylist()]
            back = [coders.unarith(coders.arith(np.frombuffer(r, np.uint8).astype(np.int64))).astype(np.uint8).tobytes() for r in raw]
            yield pa.RecordBatch.from_arrays([b.column("item_id"), pa.array([r.decode() for r in back]), pa.array([len(r) for r in back], pa.int32())], ["item_id", "text", "n"])

    return table(spark, sf, "benchmark").select("item_id", "text").mapInArrow(run, "item_id long, text string, n int")


@query(f"WITH {px('scene')}, {coded('scene')} SELECT frame_id, row, col, code - coalesce(lag(code) OVER (PARTITION BY frame_id ORDER BY row, col), 0) AS delta FROM q")
def delta_left_wrap(spark: SparkSession, sf: str) -> DataFrame:
    return linear.delta_left(q(spark, sf, "scene"), row_wrap=True).select("frame_id", "row", "col", "delta")


BOX = "full_ AS (SELECT b.frame_id, r.row::INT AS row, c.col::INT AS col FROM (SELECT frame_id, min(row) r0, max(row) r1, min(col) c0, max(col) c1 FROM q GROUP BY 1) b, LATERAL (SELECT unnest(generate_series(r0, r1)) AS row) r, LATERAL (SELECT unnest(generate_series(c0, c1)) AS col) c)"


@query(f"WITH {px('events')}, {coded('events')}, {BOX}, f AS (SELECT frame_id, row, col, code, coalesce(code, 0) AS plane FROM full_ LEFT JOIN q USING (frame_id, row, col)), g AS (SELECT *, coalesce(lag(plane) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS l, coalesce(lag(plane) OVER (PARTITION BY frame_id, col ORDER BY row), 0) AS u FROM f), n AS (SELECT *, coalesce(lag(l) OVER (PARTITION BY frame_id, col ORDER BY row), 0) AS ul FROM g) SELECT frame_id, row, col, code - (l + u - ul) AS delta FROM n WHERE code IS NOT NULL", "delta_linear_zero_fill")
def pad_zero(spark: SparkSession, sf: str) -> DataFrame:
    """Three-neighbour residuals with void pixels and borders as zeros."""
    return linear.delta_three(q(spark, sf, "events"), fill="zero").select("frame_id", "row", "col", "delta")


@query(f"WITH {px('part')}, {coded('part')}, {BOX}, f AS (SELECT frame_id, row, col, code, coalesce(last_value(code IGNORE NULLS) OVER (PARTITION BY frame_id, row ORDER BY col ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 0) AS plane FROM full_ LEFT JOIN q USING (frame_id, row, col)), g AS (SELECT *, coalesce(lag(plane) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS l, coalesce(lag(plane) OVER (PARTITION BY frame_id, col ORDER BY row), 0) AS u FROM f), n AS (SELECT *, coalesce(lag(l) OVER (PARTITION BY frame_id, col ORDER BY row), 0) AS ul FROM g) SELECT frame_id, row, col, code - floor(5e-1 * l + 75e-2 * u + -25e-2 * ul + 5e-1)::BIGINT AS delta FROM n WHERE code IS NOT NULL")
def delta_weighted(spark: SparkSession, sf: str) -> DataFrame:
    return linear.weighted(q(spark, sf, "part"), (0.5, 0.75, -0.25)).select("frame_id", "row", "col", "delta")


@query(None)
def delta_fit(spark: SparkSession, sf: str) -> DataFrame:
    """Entropy under least-squares weights beside the fixed three-neighbour ones."""
    c = q(spark, sf, "scene")
    return _table([("fitted", measures.entropy_h0(linear.weighted(c, linear.fitted(c)))), ("three", measures.entropy_h0(linear.delta_three(c)))], "weights")


@query(f"WITH {px('scene')}, {coded('scene')}, z AS (SELECT code - coalesce(lag(code) OVER (PARTITION BY frame_id // 2, row, col ORDER BY frame_id), 0) AS delta, frame_id, row, col FROM q) SELECT frame_id, row, col, delta FROM z")
def delta_prev_frame_gop(spark: SparkSession, sf: str) -> DataFrame:
    """Previous-frame residuals that start anew in every group of two frames."""
    return linear.delta_prev_frame(q(spark, sf, "scene"), gop=2).select("frame_id", "row", "col", "delta")


@query(f"WITH {px('scene')}, {coded('scene')} SELECT * FROM q", "codec_roundtrip_frames_void")
def codec_headers(spark: SparkSession, sf: str) -> DataFrame:
    """A container with frame headers: size and void frames survive, pixels come back."""
    img = images.scene(spark, sf)
    return codec.decode(codec.encode(img, codec.CodecSpec(0.1, "left"), size=(25, 240))).select("frame_id", "row", "col", "code")


for _coder in coders.CODERS:
    QUERIES[f"coder_roundtrip_{_coder}_events"] = (
        lambda s, p, c=_coder: codec.decode(codec.encode(images.events_img(s, p), codec.CodecSpec(0.1, "three", (16, 48), c))).select("frame_id", "row", "col", "code"),
        f"WITH {px('events')}, {coded('events')} SELECT * FROM q",
    )
for _mask in ("raw", "rle", "deflate", "lzma", "arith2d"):
    QUERIES[f"mask_roundtrip_{_mask}"] = (
        lambda s, p, m=_mask: codec.decode(codec.encode(images.mask_img(s, p), codec.CodecSpec(0.1, "left", (20, 50), "deflate", m))).select("frame_id", "row", "col"),
        f"SELECT frame_id, row, col FROM ({SQL['mask']})",
    )


@query(None)
def coder_choice(spark: SparkSession, sf: str) -> DataFrame:
    """Which coder wins how many blocks, by precision."""
    rows = [(str(d), codec.encode(images.scene(spark, sf), codec.CodecSpec(d, "three")).groupBy("coder").agg(F.count(F.lit(1)).alias("blocks"))) for d in (0.5, 0.1, 0.02)]
    return _table(rows, "d")


# Streams

SHOT = "SELECT event_id, ts, (user_id % 16)::INT AS row, ((hour(ts) * 3600 + minute(ts) * 60 + floor(second(ts)))::BIGINT // 1800)::INT AS col, user_id % 4 AS sensor, value AS range, event_type FROM events"


@query("SELECT epoch(date_trunc('day', ts))::BIGINT // 86400 AS day, count(*) AS n, sum(floor(value / 1e-1 + 5e-1)::BIGINT)::BIGINT AS total, min(event_id) AS first FROM events WHERE value > 0 AND value <= 75 GROUP BY 1")
def stream_frames(spark: SparkSession, sf: str) -> DataFrame:
    return streams.drain(streams.frames(streams.shots(streams.source(spark, sf))))


@query("SELECT d + o AS day, count(*) AS n, round(avg(value), 6) AS mean FROM (SELECT epoch(date_trunc('day', ts))::BIGINT // 86400 AS d, value FROM events), (VALUES (0), (-1)) v(o) GROUP BY 1")
def stream_sliding(spark: SparkSession, sf: str) -> DataFrame:
    return streams.drain(streams.sliding(streams.shots(streams.source(spark, sf))))


@query("WITH s AS (SELECT user_id % 4 AS sensor, epoch_us(ts) AS t FROM events), m AS (SELECT *, t >= lag(t) OVER w + 3600000000 OR lag(t) OVER w IS NULL AS new FROM s WINDOW w AS (PARTITION BY sensor ORDER BY t)), g AS (SELECT *, sum(new::BIGINT) OVER (PARTITION BY sensor ORDER BY t ROWS UNBOUNDED PRECEDING) AS k FROM m) SELECT sensor, min(t) AS start, max(t) + 3600000000 AS \"end\", count(*) AS n FROM g GROUP BY sensor, k")
def stream_session(spark: SparkSession, sf: str) -> DataFrame:
    return streams.drain(streams.sessions(streams.shots(streams.source(spark, sf)), "1 hour"))


@query("SELECT event_id, user_id % 4 AS sensor FROM events")
def stream_dedup(spark: SparkSession, sf: str) -> DataFrame:
    """Every shot arrives twice; the second is dropped."""
    s = streams.shots(streams.source(spark, sf, 1))
    twice = s.withColumn("event_id", F.explode(F.array("event_id", "event_id")))
    return streams.drain(streams.deduplicated(twice).select("event_id", "sensor"), "append")


@query(f"WITH s AS ({SHOT}), c AS (SELECT *, floor(range / 1e-1 + 5e-1)::BIGINT AS code FROM s WHERE range > 0 AND range <= 75) SELECT event_id, code - coalesce(lag(code) OVER (PARTITION BY row, col ORDER BY ts, event_id), 0) AS delta FROM c")
def stream_prev_delta(spark: SparkSession, sf: str) -> DataFrame:
    """Residuals against the last shot of the same pixel, whose code is kept as state over triggers."""
    return streams.drain(streams.prev_deltas(streams.shots(streams.source(spark, sf, 3))), "append")


@query(f"SELECT event_id, row, range * dz AS z, range * hs AS ground FROM ({SHOT}) JOIN ({BEAMS}) USING (row)")
def stream_calibrated(spark: SparkSession, sf: str) -> DataFrame:
    beams, _ = calibration_of(spark, sf)
    return streams.drain(streams.calibrated(streams.shots(streams.source(spark, sf, 2)), beams), "append")


@query(None)
def stream_late(spark: SparkSession, sf: str) -> DataFrame:
    """Shots a day late reach a closed frame and are left out: frames by day, the late file sent last."""
    e = table(spark, sf, "events")
    to, first = shared_dir(spark, "late"), e.agg(F.min("ts")).first()[0]
    e.where(F.col("event_id") % 10 != 0).coalesce(1).write.parquet(f"{to}/a")
    e.where(F.col("event_id") % 10 == 0).where(F.col("ts") <= F.lit(first) + F.expr("interval 1 day")).coalesce(1).write.parquet(f"{to}/b")
    s = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(to)
    return streams.drain(streams.frames(streams.shots(s)), "append")


# Sources, sinks and SQL


@query(f"WITH {px('scene')}, {coded('scene')} SELECT * FROM q WHERE frame_id BETWEEN 1 AND 2")
def sink_container(spark: SparkSession, sf: str) -> DataFrame:
    """Written clustered by frame, read back with a filter that the scan's statistics use."""
    to = shared_dir(spark, "container")
    container.sink(codec.encode(images.scene(spark, sf), codec.CodecSpec(0.1, "three")), to, frames_a_file=2)
    return codec.decode(container.load(spark, to).where("frame_id between 1 and 2")).select("frame_id", "row", "col", "code")


@query(f"WITH {px('scene')}, {coded('scene')} SELECT * FROM q WHERE frame_id = 2 AND row <= 7 AND col >= 100")
def scan_container(spark: SparkSession, sf: str) -> DataFrame:
    """Pixels straight from the data source; the filters prune blocks before they are decoded."""
    to = shared_dir(spark, "container")
    container.sink(codec.encode(images.scene(spark, sf), codec.CodecSpec(0.1, "three", (8, 40))), to)
    container.register(spark)
    return spark.read.format("shotgrid").option("path", to).load().where("frame_id = 2 and row <= 7 and col >= 100").select("frame_id", "row", "col", "code")


@query(f"WITH {px('part')}, {coded('part')} SELECT row, count(*) AS n, sum(code)::BIGINT AS total FROM q GROUP BY 1 HAVING count(*) > 10")
def sql_view(spark: SparkSession, sf: str) -> DataFrame:
    q(spark, sf, "part").createOrReplaceTempView("sg_part_codes")
    return spark.sql("SELECT row, count(*) AS n, sum(code) AS total FROM sg_part_codes GROUP BY row HAVING count(*) > 10")


@query("SELECT event_id, floor(value / 1e-1 + 5e-1)::BIGINT AS code, CASE WHEN event_id >= 500 THEN 2 * (event_id - 500) ELSE -2 * (event_id - 500) - 1 END::BIGINT AS zigzag FROM events")
def sql_functions(spark: SparkSession, sf: str) -> DataFrame:
    sg.register(spark)
    table(spark, sf, "events").createOrReplaceTempView("sg_events")
    return spark.sql("SELECT event_id, sg_code(value, 0.1D) AS code, sg_zigzag(event_id - 500) AS zigzag FROM sg_events")


@query(f"WITH {px('lineitem')}, {coded('lineitem')} SELECT frame_id, row, sum(code)::BIGINT AS total, count(*)::INT AS n FROM q GROUP BY 1, 2")
def udf_encode_bytes(spark: SparkSession, sf: str) -> DataFrame:
    """Rows of codes to bytes and back by Arrow functions."""
    f = sg.functions()
    from .functions.shipping import ship

    ship(spark)
    rows = q(spark, sf, "lineitem").groupBy("frame_id", "row").agg(F.array_sort(F.collect_list(F.struct("col", "code"))).alias("p"))
    back = rows.select("frame_id", "row", f["sg_decode_bytes"](f["sg_encode_bytes"](F.col("p.code"))).alias("v"))
    return back.select("frame_id", "row", F.aggregate("v", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.size("v").alias("n"))


@query("SELECT label, round(-sum(n / t * log2(n / t)), 6) AS h0 FROM (SELECT label, n, sum(n) OVER (PARTITION BY label) AS t FROM (SELECT label, floor(embedding[1] * 10)::BIGINT AS k, count(*) AS n FROM embeddings GROUP BY 1, 2)) GROUP BY 1")
def udaf_entropy(spark: SparkSession, sf: str) -> DataFrame:
    from .functions.shipping import ship

    ship(spark)
    e = table(spark, sf, "embeddings").select("label", F.floor(F.col("embedding")[0] * 10).alias("k"))
    return e.groupBy("label").agg(sg.functions()["sg_h0"]("k").alias("h0")).select("label", F.round("h0", 6).alias("h0"))


@query(f"WITH {px('part')}, {coded('part')} SELECT * FROM q")
def udtf_decode(spark: SparkSession, sf: str) -> DataFrame:
    """SELECT * FROM sg_decode(TABLE(container))."""
    sg.register(spark)
    codec.encode(images.part_img(spark, sf), codec.CodecSpec(0.1, "three")).createOrReplaceTempView("sg_container")
    return spark.sql("SELECT frame_id, row, col, code FROM sg_decode(TABLE(SELECT * FROM sg_container))")


@query("SELECT event_id % 3 <> 0 AS train, count(*) AS n FROM events WHERE false GROUP BY 1")
def split_sequences(spark: SparkSession, sf: str) -> DataFrame:
    """Sequences that stand on both sides of the train split: none."""
    s = learned.split(table(spark, sf, "events").withColumn("seq", F.col("user_id") % 32), "seq", 80)
    both = s.groupBy("seq").agg(F.countDistinct("train").alias("sides")).where("sides > 1")
    return s.join(both.select("seq"), "seq").groupBy("train").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT day, n, total, first FROM (SELECT epoch(date_trunc('day', ts))::BIGINT // 86400 AS day, count(*) AS n, sum(floor(value / 1e-1 + 5e-1)::BIGINT)::BIGINT AS total, min(event_id) AS first FROM events WHERE value > 0 AND value <= 75 GROUP BY 1)")
def w21_stream(spark: SparkSession, sf: str) -> DataFrame:
    """The stream of frames equals the batch over the same shots."""
    return stream_frames(spark, sf)
