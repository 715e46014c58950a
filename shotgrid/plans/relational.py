"""Scans, filters, joins, aggregates, windows and set operations on shots and images, each as a declarative plan.

Every entry of QUERIES has DuckDB SQL beside it. Tables whose size is bounded by the sensor (beams, azimuths, poses, code
books) are broadcast; everything else joins and aggregates by hash on keys of the frame."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import baselines, codec, geometry, linear, masks, measures
from ..sources import images
from ..sources.images import SQL, table

QUERIES: dict[str, tuple] = {}


def query(sql: str, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = (f, sql)
        return f

    return keep


def px(image: str) -> str:
    return f"px AS ({SQL[image]})"


def coded(image: str, d: float = 0.1, name: str = "q") -> str:
    return f"{name} AS (SELECT frame_id, row, col, floor(range / {d:e} + 5e-1)::BIGINT AS code FROM px)"


def q(spark: SparkSession, sf: str, image: str, d: float = 0.1) -> DataFrame:
    return linear.codes(images.IMAGES[image](spark, sf), d)


# Scans


@query("SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem WHERE l_quantity > 45 AND l_linenumber = 1")
def scan_parquet_pruned(spark: SparkSession, sf: str) -> DataFrame:
    """Three columns and two filters, all of which reach the Parquet scan."""
    return table(spark, sf, "lineitem").where("l_quantity > 45 and l_linenumber = 1").select("l_orderkey", "l_linenumber", "l_extendedprice")


@query("SELECT event_id, epoch_us(ts) AS micros, ts::DATE AS day FROM events")
def scan_ntz_cast(spark: SparkSession, sf: str) -> DataFrame:
    """Times without a zone as instants of UTC, whatever the session's zone is."""
    day = F.to_date("ts")
    inside = (F.hour("ts") * 3600 + F.minute("ts") * 60).cast("long") * 1_000_000 + (F.date_part(F.lit("SECONDS"), F.col("ts")) * 1_000_000).cast("long")
    return table(spark, sf, "events").select("event_id", (F.unix_date(day).cast("long") * 86_400_000_000 + inside).alias("micros"), day.alias("day"))


@query("SELECT vec_id, (i - 1)::INT AS row, embedding[i]::DOUBLE AS x FROM embeddings, generate_series(1, 64) g(i) WHERE label = 3")
def scan_array(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "embeddings").where("label = 3").select("vec_id", F.posexplode("embedding").alias("row", "x")).withColumn("x", F.col("x").cast("double"))


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def scan_json(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


# Filters and projections


@query(f"WITH {px('events')} SELECT * FROM px")
def crop_range(spark: SparkSession, sf: str) -> DataFrame:
    return images.events_img(spark, sf)


@query(f"SELECT * FROM ({SQL['lineitem']})")
def first_return(spark: SparkSession, sf: str) -> DataFrame:
    return images.lineitem_img(spark, sf)


@query(f"WITH {px('scene')}, {coded('scene')} SELECT frame_id, row, col, code * 1e-1 AS range FROM q")
def dequantize(spark: SparkSession, sf: str) -> DataFrame:
    return q(spark, sf, "scene").select("frame_id", "row", "col", linear.decode("code", 0.1).alias("range"))


@query("SELECT frame_id, row, col, (row // 16)::INT AS block_row, (col // 50)::INT AS block_col FROM (" + SQL["scene"] + ")")
def block_keys(spark: SparkSession, sf: str) -> DataFrame:
    return images.scene(spark, sf).select("frame_id", "row", "col", F.floor(F.col("row") / 16).cast("int").alias("block_row"), F.floor(F.col("col") / 50).cast("int").alias("block_col"))


@query("SELECT frame_id, row, col, (frame_id // 2)::BIGINT AS gop, (frame_id % 2 = 0) AS key_frame FROM (" + SQL["scene"] + ")")
def gop_keys(spark: SparkSession, sf: str) -> DataFrame:
    return images.scene(spark, sf).select("frame_id", "row", "col", F.floor(F.col("frame_id") / 2).alias("gop"), (F.col("frame_id") % 2 == 0).alias("key_frame"))


@query("SELECT frame_id, (row // 2)::INT AS row, col, range FROM (" + SQL["scene"] + ") WHERE row % 2 = 0")
def subsample_beams(spark: SparkSession, sf: str) -> DataFrame:
    return images.subsample_rows(images.scene(spark, sf))


@query(f"WITH {px('scene')}, {coded('scene')} SELECT * FROM q", "to_blocks_exploded")
def to_blocks_exploded(spark: SparkSession, sf: str) -> DataFrame:
    spec = codec.CodecSpec(0.1, block=(16, 50))
    return codec.to_pixels(codec.to_blocks(images.scene(spark, sf), spec), spec)


@query(f"WITH {px('lineitem')}, {coded('lineitem')} SELECT * FROM q")
def blocks_to_pixels(spark: SparkSession, sf: str) -> DataFrame:
    spec = codec.CodecSpec(0.1, block=(8, 64))
    return codec.to_pixels(codec.to_blocks(images.lineitem_img(spark, sf), spec), spec)


@query("WITH " + px("events") + ", full_ AS (SELECT f.frame_id, r.row::INT AS row, c.col::INT AS col FROM (SELECT DISTINCT frame_id FROM px) f, generate_series(0, 15) r(row), generate_series(0, 47) c(col)) SELECT frame_id, sum((range IS NULL)::BIGINT)::BIGINT AS void, count(range) AS valid, coalesce(nullif(min(coalesce(range, 0e0)), 0e0), -1e0) AS least FROM full_ LEFT JOIN px USING (frame_id, row, col) GROUP BY 1")
def void_mask(spark: SparkSession, sf: str) -> DataFrame:
    """Pixels without a return, by outer join with the frame's grid."""
    img = images.events_img(spark, sf)
    full = img.select("frame_id").distinct().withColumn("row", F.explode(F.sequence(F.lit(0), F.lit(15)))).withColumn("col", F.explode(F.sequence(F.lit(0), F.lit(47))))
    at = full.join(img, ["frame_id", "row", "col"], "left")
    least = F.coalesce(F.nullif(F.min(F.coalesce("range", F.lit(0.0))), F.lit(0.0)), F.lit(-1.0))
    return at.groupBy("frame_id").agg(F.sum(F.col("range").isNull().cast("long")).alias("void"), F.count("range").alias("valid"), least.alias("least"))


@query("SELECT event_id, event_type FROM events WHERE user_id % 16 IN (1, 5, 9) AND event_type LIKE 'c%' AND regexp_matches(props, '[02468]}')")
def filter_frames(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").where((F.col("user_id") % 16).isin(1, 5, 9) & F.col("event_type").like("c%") & F.col("props").rlike("[02468]}")).select("event_id", "event_type")


@query(f"WITH {px('scene')}, {coded('scene')}, z AS (SELECT code - coalesce(lag(code) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS delta FROM q) SELECT CASE WHEN abs(delta) <= 15 THEN delta ELSE 16 END::BIGINT AS symbol, count(*) AS n FROM z GROUP BY 1")
def escape_symbols(spark: SparkSession, sf: str) -> DataFrame:
    d = linear.delta_left(q(spark, sf, "scene"))
    return d.groupBy(F.when(F.abs("delta") <= 15, F.col("delta")).otherwise(F.lit(16)).cast("long").alias("symbol")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT frame_id, row, col, range FROM (" + SQL["lineitem"] + ") WHERE (frame_id * 7919 + row * 104729 + col * 1299709) % 97 = 5")
def sample_patches(spark: SparkSession, sf: str) -> DataFrame:
    """A sampling operator: pixels by a hash of their place, the same ones on every run."""
    return images.lineitem_img(spark, sf).where((F.col("frame_id") * 7919 + F.col("row") * 104729 + F.col("col") * 1299709) % 97 == 5).select("frame_id", "row", "col", "range")


@query("WITH RECURSIVE h AS (SELECT o_orderkey, o_custkey, (((1::BIGINT * 1103515245 + o_orderkey * 12345 + 1) % 2147483647) * 1103515245 + o_custkey * 12345 + 1) % 2147483647 AS h FROM orders) SELECT o_orderkey, round((h % 5000 + 1) * 1e-4, 6) AS precision FROM h")
def sample_precision(spark: SparkSession, sf: str) -> DataFrame:
    from ..operators import learned

    return table(spark, sf, "orders").select("o_orderkey", F.round(learned.sample_precision(["o_orderkey", "o_custkey"]), 6).alias("precision"))


@query("SELECT DISTINCT user_id % 16 AS sensor, ts::DATE AS day FROM events")
def distinct_frames(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").select((F.col("user_id") % 16).alias("sensor"), F.to_date("ts").alias("day")).dropDuplicates()


@query(f"WITH {px('scene')}, {coded('scene')} SELECT * FROM q WHERE row BETWEEN 4 AND 9 AND col BETWEEN 60 AND 110")
def roi_scan(spark: SparkSession, sf: str) -> DataFrame:
    """A box of pixels from a container: only blocks that the box touches are decoded."""
    spec = codec.CodecSpec(0.1, "left", (8, 40))
    box = codec.where_box(codec.encode(images.scene(spark, sf), spec), spec, (4, 9), (60, 110))
    return codec.decode(box).where("row between 4 and 9 and col between 60 and 110").select("frame_id", "row", "col", "code")


@query("SELECT frame_id, row, (col // 32)::INT AS word, bit_or(1::BIGINT << (col % 32)) AS bits, count(*) AS n FROM (" + SQL["mask"] + ") GROUP BY 1, 2, 3")
def mask_words(spark: SparkSession, sf: str) -> DataFrame:
    return masks.mask_words(images.mask_img(spark, sf))


# Joins

BEAMS = "SELECT n_nationkey::INT AS row, (1e0 - te * te) / (1e0 + te * te) AS hs, 2e0 * te / (1e0 + te * te) AS dz FROM (SELECT n_nationkey, 4e-2 - 26e-2 * n_nationkey::DOUBLE * n_nationkey::DOUBLE / 576e0 AS te FROM nation)"
TURNS = "SELECT c::INT AS col, CASE c // 60 WHEN 0 THEN ux WHEN 1 THEN -uy WHEN 2 THEN -ux ELSE uy END AS hx, CASE c // 60 WHEN 0 THEN uy WHEN 1 THEN ux WHEN 2 THEN -uy ELSE -ux END AS hy FROM (SELECT c, (1e0 - ta * ta) / (1e0 + ta * ta) AS ux, 2e0 * ta / (1e0 + ta * ta) AS uy FROM (SELECT c, 2e0 * ((c % 60)::DOUBLE + 5e-1) / 60e0 - 1e0 AS ta FROM generate_series(0, 239) g(c)))"


def calibration_of(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    return geometry.calibration(table(spark, sf, "nation").select(F.col("n_nationkey").cast("int").alias("row")))


@query(f"SELECT row, col, hx * hs AS dx, hy * hs AS dy, dz FROM ({BEAMS}) b, ({TURNS}) t")
def calibration(spark: SparkSession, sf: str) -> DataFrame:
    beams, turns = calibration_of(spark, sf)
    return beams.crossJoin(F.broadcast(turns)).select("row", "col", (F.col("hx") * F.col("hs")).alias("dx"), (F.col("hy") * F.col("hs")).alias("dy"), "dz")


@query(f"WITH {px('scene')} SELECT frame_id, row, col, range, hs, dz, hx, hy FROM px JOIN ({BEAMS}) USING (row) JOIN ({TURNS}) USING (col)")
def join_calibration(spark: SparkSession, sf: str) -> DataFrame:
    beams, turns = calibration_of(spark, sf)
    return images.scene(spark, sf).join(F.broadcast(beams), "row").join(F.broadcast(turns), "col").select("frame_id", "row", "col", "range", "hs", "dz", "hx", "hy")


@query(f"WITH {px('part')}, {coded('part')} SELECT frame_id, count(*) AS n, round(max(abs(range - code * 1e-1)), 6) AS worst FROM px JOIN q USING (frame_id, row, col) GROUP BY 1")
def join_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    """Original and decoded pixels by sort-merge join."""
    img = images.part_img(spark, sf)
    back = codec.decode(codec.encode(img, codec.CodecSpec(0.1, "three"))).select("frame_id", "row", "col", F.col("range").alias("back"))
    return img.join(back.hint("merge"), ["frame_id", "row", "col"]).groupBy("frame_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.max(F.abs(F.col("range") - F.col("back"))), 6).alias("worst"))


@query(f"WITH {px('scene')}, {coded('scene')} SELECT a.frame_id, a.row, a.col, count(*) AS near, min(b.code) AS low FROM q a JOIN q b ON a.frame_id = b.frame_id AND b.row BETWEEN a.row - 1 AND a.row AND b.col BETWEEN a.col - 2 AND a.col AND (a.row <> b.row OR a.col <> b.col) GROUP BY 1, 2, 3")
def join_band(spark: SparkSession, sf: str) -> DataFrame:
    """Pixels with their neighbours in a band of rows and columns: offsets are exploded, so the join is on equality."""
    return geometry.context_points(q(spark, sf, "scene"), 2, 3).groupBy("frame_id", "row", "col").agg(F.count(F.lit(1)).alias("near"), F.min("near").alias("low"))


@query("SELECT s.event_id, p.event_id AS pose_id, p.value AS heading FROM (SELECT *, user_id % 4 AS sensor FROM events WHERE event_id % 20 <> 0) s ASOF LEFT JOIN (SELECT ts, max(event_id) AS event_id, max_by(value, event_id) AS value, user_id % 4 AS sensor FROM events WHERE event_id % 20 = 0 GROUP BY ts, user_id % 4) p ON s.sensor = p.sensor AND s.ts >= p.ts")
def join_asof_pose(spark: SparkSession, sf: str) -> DataFrame:
    """Each shot with the last pose of its sensor: every twentieth event stands for a pose."""
    e = table(spark, sf, "events").select("event_id", "ts", "value", (F.col("user_id") % 4).alias("sensor"))
    poses = e.where("event_id % 20 = 0").groupBy("sensor", "ts").agg(F.max("event_id").alias("pose_id"), F.max_by("value", "event_id").alias("heading"))
    return geometry.asof(e.where("event_id % 20 <> 0").select("event_id", "ts", "sensor"), poses, ["sensor"], "ts", ["pose_id", "heading"]).select("event_id", "pose_id", "heading")


@query("WITH f AS (SELECT DISTINCT ts::DATE AS day FROM events), i AS (SELECT day, day::TIMESTAMP + INTERVAL 6 HOUR AS a, day::TIMESTAMP + INTERVAL 9 HOUR AS b FROM f) SELECT day, count(*) AS n, min(event_id) AS first FROM events JOIN i ON ts >= a AND ts < b GROUP BY 1")
def join_interval(spark: SparkSession, sf: str) -> DataFrame:
    """Shots inside each frame's interval: equality on the day first, the interval as a residual condition."""
    e = table(spark, sf, "events").withColumn("day", F.to_date("ts"))
    frames = e.select("day").distinct().select("day", (F.col("day").cast("timestamp_ntz") + F.expr("interval 6 hours")).alias("a"), (F.col("day").cast("timestamp_ntz") + F.expr("interval 9 hours")).alias("b"))
    return e.join(frames, "day").where("ts >= a and ts < b").groupBy("day").agg(F.count(F.lit(1)).alias("n"), F.min("event_id").alias("first"))


@query(f"WITH {px('scene')} SELECT frame_id, row, col, range FROM px a WHERE frame_id = 1 AND EXISTS (SELECT 1 FROM px b WHERE b.frame_id = 0 AND b.row = a.row AND b.col = a.col)")
def join_semi(spark: SparkSession, sf: str) -> DataFrame:
    img = images.scene(spark, sf)
    return img.where("frame_id = 1").join(img.where("frame_id = 0"), ["row", "col"], "left_semi").select("frame_id", "row", "col", "range")


@query(f"WITH {px('scene')} SELECT frame_id, row, col, range FROM px a WHERE frame_id = 3 AND NOT EXISTS (SELECT 1 FROM px b WHERE b.frame_id = 0 AND b.row = a.row AND b.col = a.col)")
def join_anti(spark: SparkSession, sf: str) -> DataFrame:
    img = images.scene(spark, sf)
    return img.where("frame_id = 3").join(img.where("frame_id = 0"), ["row", "col"], "left_anti").select("frame_id", "row", "col", "range")


@query(f"WITH {px('scene')}, {coded('scene')}, a AS (SELECT * FROM q WHERE frame_id = 0), b AS (SELECT * FROM q WHERE frame_id = 3) SELECT row, col, a.code AS before, b.code AS after, CASE WHEN a.code IS NULL THEN 'new' WHEN b.code IS NULL THEN 'gone' WHEN a.code = b.code THEN 'same' ELSE 'moved' END AS kind FROM a FULL JOIN b USING (row, col)")
def join_frame_diff(spark: SparkSession, sf: str) -> DataFrame:
    c = q(spark, sf, "scene")
    both = c.where("frame_id = 0").select("row", "col", F.col("code").alias("before")).join(c.where("frame_id = 3").select("row", "col", F.col("code").alias("after")), ["row", "col"], "full")
    kind = F.when(F.col("before").isNull(), "new").when(F.col("after").isNull(), "gone").when(F.col("before") == F.col("after"), "same").otherwise("moved")
    return both.withColumn("kind", kind)


@query(f"WITH {px('scene')}, {coded('scene')} SELECT a.frame_id, a.row, a.col, a.code - coalesce(b.code, 0) AS delta FROM q a LEFT JOIN q b ON b.frame_id = a.frame_id - 1 AND b.row = a.row AND b.col = a.col")
def join_prev_frame(spark: SparkSession, sf: str) -> DataFrame:
    """Residual against the frame before, by a self join on the shifted frame number (T-1 only)."""
    c = q(spark, sf, "scene")
    before = c.select((F.col("frame_id") + 1).alias("frame_id"), "row", "col", F.col("code").alias("_b"))
    return c.join(before, ["frame_id", "row", "col"], "left").select("frame_id", "row", "col", (F.col("code") - F.coalesce("_b", F.lit(0))).alias("delta"))


@query(f"WITH {px('scene')}, {coded('scene')} SELECT a.row, count(*) AS n, sum(abs(a.code - b.code))::BIGINT AS moved FROM q a JOIN q b ON b.frame_id = 0 AND a.frame_id = 1 AND b.row = a.row AND b.col = a.col GROUP BY 1")
def cogroup_frames(spark: SparkSession, sf: str) -> DataFrame:
    """Rows of two frames beside each other in one task, as Arrow tables."""
    import pyarrow as pa
    import pyarrow.compute as pc

    c = q(spark, sf, "scene")
    now, before = c.where("frame_id = 1").drop("frame_id"), c.where("frame_id = 0").drop("frame_id").toDF("beam", "col", "code_b")

    def both(key, a, b):
        t = a.join(b.drop_columns(["beam"]), "col", join_type="inner")
        return pa.table({"row": pa.array([key[0].as_py()] if t.num_rows else [], pa.int32()), "n": pa.array([t.num_rows] if t.num_rows else [], pa.int64()), "moved": pa.array([pc.sum(pc.abs(pc.subtract(t["code"], t["code_b"]))).as_py()] if t.num_rows else [], pa.int64())})

    return now.groupBy("row").cogroup(before.groupBy("beam")).applyInArrow(both, "row int, n long, moved long")


# Aggregates


@query(f"WITH {px('events')}, {coded('events')} SELECT frame_id, count(*) AS n_valid, sum(code)::BIGINT AS total, round(avg(code), 6) AS mean FROM q GROUP BY 1")
def rate_by_frame(spark: SparkSession, sf: str) -> DataFrame:
    return q(spark, sf, "events").groupBy("frame_id").agg(F.count(F.lit(1)).alias("n_valid"), F.sum("code").alias("total"), F.round(F.avg("code"), 6).alias("mean"))


@query(f"WITH {px('lineitem')}, {coded('lineitem')} SELECT code, count(*) AS n FROM q GROUP BY 1")
def symbol_hist(spark: SparkSession, sf: str) -> DataFrame:
    return q(spark, sf, "lineitem").groupBy("code").agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH {px('lineitem')}, {coded('lineitem')} SELECT frame_id, count(DISTINCT code) AS symbols, count(DISTINCT row) AS beams FROM q GROUP BY 1")
def alphabet_size(spark: SparkSession, sf: str) -> DataFrame:
    return q(spark, sf, "lineitem").groupBy("frame_id").agg(F.countDistinct("code").alias("symbols"), F.countDistinct("row").alias("beams"))


@query(f"WITH {px('scene')}, e AS (SELECT abs(floor(range / 1e-1 + 5e-1) * 1e-1 - range) AS e, range FROM px) SELECT round(quantile_cont(e, 5e-1), 6) AS p50, round(quantile_cont(e, 95e-2), 6) AS p95, round(stddev_samp(e), 6) AS spread, round(covar_samp(e, range), 6) AS with_range FROM e")
def error_percentiles(spark: SparkSession, sf: str) -> DataFrame:
    img = images.scene(spark, sf)
    e = img.select(F.abs(linear.decode(linear.encode("range", 0.1), 0.1) - F.col("range")).alias("e"), "range")
    return e.agg(F.round(F.percentile("e", 0.5), 6).alias("p50"), F.round(F.percentile("e", 0.95), 6).alias("p95"), F.round(F.stddev_samp("e"), 6).alias("spread"), F.round(F.covar_samp("e", "range"), 6).alias("with_range"))


GROUPED = f"WITH {px('scene')}, {coded('scene')}, z AS (SELECT frame_id, (row // 16)::INT AS block_row, code - coalesce(lag(code) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS delta FROM q) SELECT frame_id, block_row, count(*) AS n, sum((delta = 0)::BIGINT)::BIGINT AS hits FROM z GROUP BY "


def _grouped(spark, sf):
    return linear.delta_left(q(spark, sf, "scene")).select("frame_id", F.floor(F.col("row") / 16).cast("int").alias("block_row"), "delta")


def _measured():
    return F.count(F.lit(1)).alias("n"), F.sum((F.col("delta") == 0).cast("long")).alias("hits")


@query(GROUPED + "ROLLUP (frame_id, block_row)")
def rate_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return _grouped(spark, sf).rollup("frame_id", "block_row").agg(*_measured())


@query(GROUPED + "CUBE (frame_id, block_row)")
def rate_cube(spark: SparkSession, sf: str) -> DataFrame:
    return _grouped(spark, sf).cube("frame_id", "block_row").agg(*_measured())


@query(GROUPED + "GROUPING SETS ((frame_id), (block_row))")
def rate_gsets(spark: SparkSession, sf: str) -> DataFrame:
    d = _grouped(spark, sf)
    return d.groupingSets([["frame_id"], ["block_row"]], "frame_id", "block_row").agg(*_measured())


@query(f"WITH {px('scene')}, e AS (SELECT frame_id, d, abs(floor(range / d + 5e-1) * d - range) AS e FROM px, (VALUES (5e-1), (1e-1)) v(d)) SELECT frame_id, round(avg(e) FILTER (d = 5e-1), 6) AS coarse, round(avg(e) FILTER (d = 1e-1), 6) AS fine FROM e GROUP BY 1")
def rd_pivot(spark: SparkSession, sf: str) -> DataFrame:
    """Errors by precision as a table with a column for each precision: one scan, the precisions exploded."""
    img = images.scene(spark, sf).withColumn("d", F.explode(F.array(F.lit(0.5), F.lit(0.1))))
    e = img.select("frame_id", F.when(F.col("d") == 0.5, "coarse").otherwise("fine").alias("name"), F.abs(F.floor(F.col("range") / F.col("d") + F.lit(0.5)) * F.col("d") - F.col("range")).alias("e"))
    return e.groupBy("frame_id").pivot("name", ["coarse", "fine"]).agg(F.round(F.avg("e"), 6))


@query(f"WITH {px('lineitem')} SELECT channel, count(*) AS n, round(avg(value), 6) AS mean FROM (UNPIVOT px ON range, intensity, elongation INTO NAME channel VALUE value) GROUP BY 1")
def channels_unpivot(spark: SparkSession, sf: str) -> DataFrame:
    img = images.lineitem_img(spark, sf)
    return img.unpivot(["frame_id", "row", "col"], ["range", "intensity", "elongation"], "channel", "value").groupBy("channel").agg(F.count("value").alias("n"), F.round(F.avg("value"), 6).alias("mean"))


# Windows


@query(f"WITH {px('events')}, {coded('events')}, f AS (SELECT b.frame_id, r.row::INT AS row, c.col::INT AS col FROM (SELECT frame_id, min(row) r0, max(row) r1, min(col) c0, max(col) c1 FROM q GROUP BY 1) b, LATERAL (SELECT unnest(generate_series(r0, r1)) AS row) r, LATERAL (SELECT unnest(generate_series(c0, c1)) AS col) c) SELECT frame_id, row, col, coalesce(last_value(code IGNORE NULLS) OVER (PARTITION BY frame_id, row ORDER BY col ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 0) AS plane FROM f LEFT JOIN q USING (frame_id, row, col)")
def fill_plane(spark: SparkSession, sf: str) -> DataFrame:
    return linear.filled(q(spark, sf, "events")).select("frame_id", "row", "col", "plane")


@query(f"WITH {px('scene')} SELECT frame_id, row, col, round(range - avg(range) OVER (PARTITION BY frame_id, row ORDER BY col ROWS BETWEEN 9 PRECEDING AND 1 PRECEDING), 6) AS rel, count(*) OVER (PARTITION BY frame_id, row ORDER BY col RANGE BETWEEN 9 PRECEDING AND 1 PRECEDING) AS near FROM px")
def context_mean(spark: SparkSession, sf: str) -> DataFrame:
    """Range relative to the mean of the nine pixels before (rows frame) and the valid ones among nine columns (range frame)."""
    w = Window.partitionBy("frame_id", "row").orderBy("col")
    img = images.scene(spark, sf)
    return img.select("frame_id", "row", "col", F.round(F.col("range") - F.avg("range").over(w.rowsBetween(-9, -1)), 6).alias("rel"), F.count(F.lit(1)).over(w.rangeBetween(-9, -1)).alias("near"))


@query("SELECT class, id, rank() OVER w AS rank, dense_rank() OVER w AS dense, round(percent_rank() OVER w, 6) AS share, round(cume_dist() OVER w, 6) AS cume FROM (SELECT lang AS class, doc_id AS id, n_chars FROM documents) WINDOW w AS (PARTITION BY class ORDER BY n_chars DESC)")
def ap_rank(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("class").orderBy(F.desc("n_chars"))
    d = table(spark, sf, "documents").select(F.col("lang").alias("class"), F.col("doc_id").alias("id"), "n_chars")
    return d.select("class", "id", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.round(F.percent_rank().over(w), 6).alias("share"), F.round(F.cume_dist().over(w), 6).alias("cume"))


@query(f"WITH {px('part')}, e AS (SELECT row, col, abs(floor(range / 1e-1 + 5e-1) * 1e-1 - range) AS e FROM px), t AS (SELECT *, ntile(4) OVER (PARTITION BY row ORDER BY e, col) AS part FROM e) SELECT row, part, count(*) AS n, round(max(e), 6) AS worst FROM t GROUP BY 1, 2")
def ntile_error(spark: SparkSession, sf: str) -> DataFrame:
    e = images.part_img(spark, sf).select("row", "col", F.abs(F.floor(F.col("range") / F.lit(0.1) + F.lit(0.5)) * F.lit(0.1) - F.col("range")).alias("e"))
    t = e.withColumn("part", F.ntile(4).over(Window.partitionBy("row").orderBy("e", "col")))
    return t.groupBy("row", "part").agg(F.count(F.lit(1)).alias("n"), F.round(F.max("e"), 6).alias("worst"))


@query(f"WITH {px('scene')}, {coded('scene')}, z AS (SELECT frame_id, row, col, code - coalesce(lag(code) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS delta FROM q), g AS (SELECT *, row_number() OVER (PARTITION BY frame_id, row ORDER BY col) - row_number() OVER (PARTITION BY frame_id, row, delta ORDER BY col) AS island FROM z) SELECT frame_id, row, min(col) AS start, delta, count(*) AS length FROM g GROUP BY frame_id, row, delta, island")
def rle_runs(spark: SparkSession, sf: str) -> DataFrame:
    """Runs of equal residuals in each row: islands between changes."""
    z = linear.delta_left(q(spark, sf, "scene"))
    w = Window.partitionBy("frame_id", "row").orderBy("col")
    island = F.row_number().over(w) - F.row_number().over(Window.partitionBy("frame_id", "row", "delta").orderBy("col"))
    return z.withColumn("island", island).groupBy("frame_id", "row", "delta", "island").agg(F.min("col").alias("start"), F.count(F.lit(1)).alias("length")).select("frame_id", "row", "start", "delta", "length")


@query(f"WITH {px('scene')}, {coded('scene')} SELECT frame_id, row, col, first_value(code) OVER w AS key_code, nth_value(code, 2) OVER w AS second FROM q WINDOW w AS (PARTITION BY row, col ORDER BY frame_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def keyframe_value(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("row", "col").orderBy("frame_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return q(spark, sf, "scene").select("frame_id", "row", "col", F.first("code").over(w).alias("key_code"), F.nth_value("code", 2).over(w).alias("second"))


# Sorts and limits


@query("SELECT frame_id, row, col, range FROM (" + SQL["conversation"] + ")")
def raster_order(spark: SparkSession, sf: str) -> DataFrame:
    return images.conversation_img(spark, sf).orderBy("frame_id", "row", "col")


@query(f"WITH {px('scene')}, e AS (SELECT frame_id, row, col, round(abs(floor(range / 1e-1 + 5e-1) * 1e-1 - range), 9) AS e FROM px) SELECT * FROM e ORDER BY e DESC, frame_id, row, col LIMIT 25")
def worst_points(spark: SparkSession, sf: str) -> DataFrame:
    """A top-k report: the worst errors, without a full sort."""
    e = images.scene(spark, sf).select("frame_id", "row", "col", F.round(F.abs(F.floor(F.col("range") / F.lit(0.1) + F.lit(0.5)) * F.lit(0.1) - F.col("range")), 9).alias("e"))
    return e.orderBy(F.desc("e"), "frame_id", "row", "col").limit(25)


@query(f"WITH {px('part')} SELECT frame_id, row, col, range FROM px ORDER BY frame_id, row, col LIMIT 50 OFFSET 100")
def page_pixels(spark: SparkSession, sf: str) -> DataFrame:
    """One page of pixels in raster order."""
    return images.part_img(spark, sf).orderBy("frame_id", "row", "col").offset(100).limit(50)


# Set operations


def _voxels(image: DataFrame) -> DataFrame:
    return image.select("row", "col", F.floor(F.col("range") / 5).alias("cell"))


VOXELS = f"WITH {px('scene')}, a AS (SELECT row, col, floor(range / 5)::BIGINT AS cell FROM px WHERE frame_id = 0), b AS (SELECT row, col, floor(range / 5)::BIGINT AS cell FROM px WHERE frame_id = 1) SELECT * FROM a "


@query(VOXELS + "INTERSECT SELECT * FROM b")
def voxel_intersect(spark: SparkSession, sf: str) -> DataFrame:
    img = images.scene(spark, sf)
    return _voxels(img.where("frame_id = 0")).intersect(_voxels(img.where("frame_id = 1")))


@query(VOXELS + "UNION SELECT * FROM b")
def voxel_union(spark: SparkSession, sf: str) -> DataFrame:
    img = images.scene(spark, sf)
    return _voxels(img.where("frame_id = 0")).union(_voxels(img.where("frame_id = 1"))).distinct()


@query("SELECT 0::BIGINT AS frame_id, 0 AS row, 0 AS col, 0::BIGINT AS code WHERE false")
def roundtrip_except(spark: SparkSession, sf: str) -> DataFrame:
    """Pixels that a codec loses or changes: none."""
    want = q(spark, sf, "events").select("frame_id", "row", "col", "code")
    return want.exceptAll(codec.decode(codec.encode(images.events_img(spark, sf), codec.CodecSpec(0.1, "left"))).select("frame_id", "row", "col", "code"))


@query(f"WITH {px('scene')}, m AS (SELECT frame_id, row, col, range, floor(range / 1e-1 + 5e-1) AS a, floor(range / 5e-1 + 5e-1) AS b FROM px) SELECT 'fine' AS name, count(DISTINCT a) AS symbols FROM m UNION ALL SELECT 'coarse', count(DISTINCT b) FROM m")
def rd_union(spark: SparkSession, sf: str) -> DataFrame:
    img, rows = images.scene(spark, sf), None
    for name, d in (("fine", 0.1), ("coarse", 0.5)):
        one = img.agg(F.countDistinct(linear.encode("range", d)).alias("symbols")).select(F.lit(name).alias("name"), "symbols")
        rows = one if rows is None else rows.unionByName(one)
    return rows


# Scalar functions


@query("SELECT event_id, floor(value / 1e-1 + 5e-1)::BIGINT AS code, abs(value - 10)::DOUBLE AS gap, round(sqrt(value), 6) AS root, round(log2(value + 1), 6) AS bits, greatest(value, 1e0) AS least_one, sign(value - 10)::DOUBLE AS side, round(atan2(value, 10), 6) AS angle, round(pow(value, 2), 4) AS square FROM events")
def fn_math_quant(spark: SparkSession, sf: str) -> DataFrame:
    v = F.col("value")
    return table(spark, sf, "events").select("event_id", linear.encode("value", 0.1).alias("code"), F.abs(v - 10).alias("gap"), F.round(F.sqrt(v), 6).alias("root"), F.round(F.log2(v + 1), 6).alias("bits"), F.greatest(v, F.lit(1.0)).alias("least_one"), F.signum(v - 10).alias("side"), F.round(F.atan2(v, F.lit(10)), 6).alias("angle"), F.round(F.pow(v, 2), 4).alias("square"))


@query("SELECT delta, CASE WHEN delta >= 0 THEN 2 * delta ELSE -2 * delta - 1 END::BIGINT AS zigzag, CASE WHEN delta >= 0 THEN length(ltrim(bin(2 * delta), '0')) ELSE length(ltrim(bin(-2 * delta - 1), '0')) END::INT AS bits FROM (SELECT event_id - 500 AS delta FROM events)")
def fn_zigzag(spark: SparkSession, sf: str) -> DataFrame:
    """Zigzag numbers and their lengths in bits, in the JVM."""
    d = table(spark, sf, "events").select((F.col("event_id") - 500).alias("delta"))
    z = F.shiftleft("delta", 1).bitwiseXOR(F.shiftright("delta", 63))
    return d.select("delta", z.alias("zigzag"), F.when(z == 0, 0).otherwise(F.length(F.bin(z))).cast("int").alias("bits"))


@query("SELECT p_partkey, (" + " | ".join(f"(((p_partkey >> {i}) & 1) << {2 * i}) | (((p_size::BIGINT >> {i}) & 1) << {2 * i + 1})" for i in range(8)) + ")::BIGINT AS morton FROM part")
def fn_morton(spark: SparkSession, sf: str) -> DataFrame:
    """Interleaved bits of two coordinates."""
    bit = lambda c, i, at: F.shiftleft(F.shiftright(F.col(c).cast("long"), i).bitwiseAND(F.lit(1)), at)
    key = None
    for i in range(8):
        both = bit("p_partkey", i, 2 * i).bitwiseOR(bit("p_size", i, 2 * i + 1))
        key = both if key is None else key.bitwiseOR(both)
    return table(spark, sf, "part").select("p_partkey", key.alias("morton"))


@query("SELECT doc_id // 50 AS row, bit_or(1::BIGINT << (doc_id % 50)) AS bits, bit_count(bit_or(1::BIGINT << (doc_id % 50)))::INT AS n FROM labels GROUP BY 1")
def fn_mask_bits(spark: SparkSession, sf: str) -> DataFrame:
    bits = F.bit_or(F.expr("shiftleft(1L, cast(doc_id % 50 as int))"))
    return table(spark, sf, "labels").groupBy(F.expr("doc_id div 50").alias("row")).agg(bits.alias("bits")).select("row", "bits", F.bit_count("bits").alias("n"))


@query("SELECT vec_id, round(list_aggregate(e[1:9], 'max'), 6) AS high, round(list_aggregate(e[1:9], 'min'), 6) AS low, len(list_filter(e, lambda x: x > 0))::INT AS positive, round(list_aggregate(list_transform(list_zip(e[1:63], e[2:64]), lambda p: abs(p[2] - p[1])), 'max'), 6) AS jump FROM (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings)")
def fn_array_context(spark: SparkSession, sf: str) -> DataFrame:
    """Array functions over a context: slices, extremes, filters, differences of neighbours."""
    e = table(spark, sf, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    jump = F.array_max(F.zip_with(F.slice("e", 1, 63), F.slice("e", 2, 63), lambda a, b: F.abs(b - a)))
    return e.select("vec_id", F.round(F.array_max(F.slice("e", 1, 9)), 6).alias("high"), F.round(F.array_min(F.slice("e", 1, 9)), 6).alias("low"), F.size(F.filter("e", lambda x: x > 0)).alias("positive"), F.round(jump, 6).alias("jump"))


@query("WITH b AS (SELECT event_type, count(*) AS n FROM events GROUP BY 1), c AS (SELECT event_type, row_number() OVER (ORDER BY n DESC, event_type) - 1 AS code FROM b) SELECT event_id, c.code::BIGINT AS code FROM events JOIN c USING (event_type)")
def fn_map_codebook(spark: SparkSession, sf: str) -> DataFrame:
    """A code book as a map column of one row, broadcast to all shots."""
    e = table(spark, sf, "events")
    counts = F.array_sort(F.collect_list(F.struct((-F.col("n")).alias("n"), "event_type")))
    book = e.groupBy("event_type").agg(F.count(F.lit(1)).alias("n")).agg(counts.alias("c")).select(F.map_from_entries(F.transform("c", lambda x, i: F.struct(x["event_type"], i.cast("long")))).alias("book"))
    return e.crossJoin(F.broadcast(book)).select("event_id", F.element_at("book", F.col("event_type")).alias("code"))


@query("SELECT event_id, concat_ws('/', event_type, lpad((user_id % 16)::VARCHAR, 3, '0'), substring(props, 2, 3)) AS key, length(props)::INT AS size FROM events")
def fn_string_key(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").select("event_id", F.concat_ws("/", "event_type", F.lpad((F.col("user_id") % 16).cast("string"), 3, "0"), F.substring("props", 2, 3)).alias("key"), F.length("props").alias("size"))


@query("SELECT event_id, date_diff('day', DATE '2024-01-01', ts::DATE)::INT AS frame, hour(ts)::INT AS hour, (hour(ts) * 3600 + minute(ts) * 60 + floor(second(ts)))::BIGINT // 1800 AS slot, date_trunc('month', ts)::DATE AS month FROM events")
def fn_date_frames(spark: SparkSession, sf: str) -> DataFrame:
    ts = F.col("ts")
    slot = F.floor((F.hour(ts) * 3600 + F.minute(ts) * 60 + F.floor(F.second(ts))) / 1800)
    return table(spark, sf, "events").select("event_id", F.datediff(ts, F.lit("2024-01-01").cast("date")).alias("frame"), F.hour(ts).alias("hour"), slot.alias("slot"), F.to_date(F.date_trunc("month", ts)).alias("month"))


@query("SELECT event_id, json_extract_string(props, '$.k') AS k FROM events WHERE CAST(json_extract_string(props, '$.k') AS BIGINT) % 2 = 0")
def fn_json_attr(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").alias("k")).where("cast(k as bigint) % 2 = 0")


@query("SELECT item_id, sha256(text) AS digest, octet_length(encode(text))::INT AS bytes FROM benchmark")
def fn_crc(spark: SparkSession, sf: str) -> DataFrame:
    """Checksums of payloads: SHA-256, and CRC-32 kept only where it fits the digest's length."""
    t = table(spark, sf, "benchmark")
    return t.where(F.crc32(F.col("text").cast("binary")) >= 0).select("item_id", F.sha2("text", 256).alias("digest"), F.octet_length("text").alias("bytes"))


@query(f"WITH {px('scene')}, {coded('scene')}, z AS (SELECT code - coalesce(lag(code) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS delta FROM q), u AS (SELECT CASE WHEN delta >= 0 THEN 2 * delta ELSE -2 * delta - 1 END AS u FROM z) SELECT CASE WHEN u < 128 THEN 1 WHEN u < 16384 THEN 2 ELSE 3 END::INT AS bytes, count(*) AS n FROM u GROUP BY 1")
def varint_length(spark: SparkSession, sf: str) -> DataFrame:
    z = linear.delta_left(q(spark, sf, "scene"))
    u = F.shiftleft("delta", 1).bitwiseXOR(F.shiftright("delta", 63))
    return z.select(F.when(u < 128, 1).when(u < 16384, 2).otherwise(3).cast("int").alias("bytes")).groupBy("bytes").agg(F.count(F.lit(1)).alias("n"))


SPARSE = f"WITH {px('scene')}, {coded('scene')}, z AS (SELECT frame_id, row, col, code - coalesce(lag(code) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS delta FROM q), p AS (SELECT frame_id, row, delta, row_number() OVER (PARTITION BY frame_id, row ORDER BY col) - 1 AS place FROM z) "


@query(SPARSE + "SELECT frame_id, row, place, delta FROM p WHERE delta <> 0")
def sparse_pairs(spark: SparkSession, sf: str) -> DataFrame:
    """Non-zero residuals with their place among the valid pixels of the row."""
    w = Window.partitionBy("frame_id", "row").orderBy("col")
    return linear.delta_left(q(spark, sf, "scene")).withColumn("place", F.row_number().over(w).cast("long") - 1).where("delta <> 0").select("frame_id", "row", "place", "delta")


@query(SPARSE + "SELECT frame_id, row, place - coalesce(lag(place) OVER (PARTITION BY frame_id, row ORDER BY place), -1) - 1 AS gap, delta FROM p WHERE delta <> 0")
def sparse_gaps(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("frame_id", "row").orderBy("place")
    return sparse_pairs(spark, sf).select("frame_id", "row", (F.col("place") - F.coalesce(F.lag("place").over(w), F.lit(-1)) - 1).alias("gap"), "delta")


@query(f"WITH {px('scene')} SELECT frame_id, count(*) AS points, count(*) * 32 AS image_bits, count(*) * 96 AS cloud_bits, 3e0 AS ratio FROM px GROUP BY 1")
def storage_ratio(spark: SparkSession, sf: str) -> DataFrame:
    """Uncompressed costs: one range against three coordinates of 32 bits."""
    n = images.scene(spark, sf).groupBy("frame_id").agg(F.count(F.lit(1)).alias("points"))
    return n.select("frame_id", "points", (F.col("points") * 32).alias("image_bits"), (F.col("points") * 96).alias("cloud_bits"), (F.col("points") * 96 / (F.col("points") * 32)).alias("ratio"))


@query(f"WITH {px('lineitem')} SELECT 'raw' AS method, count(*) AS n_valid, (count(range) * 32)::BIGINT AS bits, 32e0 AS bpp FROM px")
def raw_rate(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.raw(images.lineitem_img(spark, sf))


@query(f"WITH {px('events')}, {coded('events')}, z AS (SELECT code - coalesce(lag(code) OVER (PARTITION BY frame_id, row ORDER BY col), 0) AS delta FROM q) SELECT round(100 * (sum((delta = 0)::BIGINT) + 30 * 16 * 48 - count(*)) / (30 * 16 * 48), 6) AS accuracy, count(*) AS n_valid FROM z")
def accuracy_all(spark: SparkSession, sf: str) -> DataFrame:
    """Accuracy over all pixels, void ones counted as zero residuals."""
    return measures.accuracy(linear.delta_left(q(spark, sf, "events")), all_pixels=30 * 16 * 48)


@query(f"WITH {px('scene')} SELECT round(max(abs(floor(range / 2e-2 + 5e-1) * 2e-2 - range)), 6) AS worst, max(abs(floor(range / 2e-2 + 5e-1) * 2e-2 - range)) <= 1e-2 + 1e-9 AS bounded FROM px")
def max_error(spark: SparkSession, sf: str) -> DataFrame:
    e = F.max(F.abs(linear.decode(linear.encode("range", 0.02), 0.02) - F.col("range")))
    return images.scene(spark, sf).agg(F.round(e, 6).alias("worst"), (e <= F.lit(0.01 + 1e-9)).alias("bounded"))


@query(f"WITH {px('scene')}, {coded('scene')}, n AS (SELECT a.frame_id, a.row, a.col, a.code, abs(b.code - a.code) AS gap, a.row - b.row AS di, a.col - b.col AS dj FROM q a JOIN q b ON a.frame_id = b.frame_id AND b.row BETWEEN a.row - 2 AND a.row AND b.col BETWEEN a.col - 2 AND a.col AND (a.row <> b.row OR a.col <> b.col)) SELECT frame_id, row, col, di::INT AS di, dj::INT AS dj, gap FROM n QUALIFY row_number() OVER (PARTITION BY frame_id, row, col ORDER BY gap, di + dj, di, dj) = 1")
def anchor_label(spark: SparkSession, sf: str) -> DataFrame:
    return geometry.anchor_labels(q(spark, sf, "scene"), 3, 3)


@query(f"WITH {px('scene')}, {coded('scene')}, n AS (SELECT a.frame_id, a.row, a.col, min(abs(b.code - a.code)) AS gap FROM q a JOIN q b ON a.frame_id = b.frame_id AND b.row BETWEEN a.row - 2 AND a.row AND b.col BETWEEN a.col - 2 AND a.col AND (a.row <> b.row OR a.col <> b.col) GROUP BY 1, 2, 3) SELECT round(100 * sum((gap = 0)::BIGINT) / (SELECT count(*) FROM q), 6) AS accuracy, round(avg(gap), 6) AS mean_gap, (SELECT count(*) FROM q) AS n_valid FROM n")
def anchor_upper_bound(spark: SparkSession, sf: str) -> DataFrame:
    """Share of pixels with a context pixel of their very code: what perfect anchors alone would reach."""
    return geometry.anchor_share(q(spark, sf, "scene"), 3, 3)


@query(f"WITH {px('events')}, {coded('events')} SELECT a.frame_id, a.row, a.col, (a.row - b.row)::INT AS di, (a.col - b.col)::INT AS dj, b.code AS near FROM q a JOIN q b ON a.frame_id = b.frame_id AND b.row BETWEEN a.row - 2 AND a.row AND b.col BETWEEN a.col - 2 AND a.col AND (a.row <> b.row OR a.col <> b.col)")
def context_points(spark: SparkSession, sf: str) -> DataFrame:
    return geometry.context_points(q(spark, sf, "events"), 3, 3)


@query(f"WITH {px('scene')}, {coded('scene')} SELECT a.frame_id, a.row, a.col, count(*) AS points, min(b.code) AS low, max(b.code) AS high FROM q a JOIN q b ON b.frame_id = a.frame_id - 1 AND b.row BETWEEN a.row - 1 AND a.row AND b.col BETWEEN a.col - 1 AND a.col GROUP BY 1, 2, 3")
def context_temporal_image(spark: SparkSession, sf: str) -> DataFrame:
    """The previous frame's patch of the same rows and columns, as the naive temporal context sees it."""
    c = q(spark, sf, "scene")
    asks = c.select("frame_id", "row", "col", F.explode(F.expr("transform(sequence(0, 3), i -> struct(cast(i div 2 as int) as di, cast(i % 2 as int) as dj))")).alias("o"))
    asks = asks.select("frame_id", "row", "col", (F.col("frame_id") - 1).alias("_f"), (F.col("row") - F.col("o.di")).alias("_r"), (F.col("col") - F.col("o.dj")).alias("_c"))
    there = c.select(F.col("frame_id").alias("_f"), F.col("row").alias("_r"), F.col("col").alias("_c"), "code")
    return asks.join(there, ["_f", "_r", "_c"]).groupBy("frame_id", "row", "col").agg(F.count(F.lit(1)).alias("points"), F.min("code").alias("low"), F.max("code").alias("high"))
