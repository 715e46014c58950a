"""Range images built from the given tables, in pixel form: frame_id, row, col, range (metres; void pixels are absent)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

MAX_RANGE = 75.0


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def crop(df: DataFrame, max_range: float = MAX_RANGE) -> DataFrame:
    """Pixels with a range in (0, max_range]; others, NaN and null are void."""
    return df.where((F.col("range") > 0) & (F.col("range") <= max_range))


def first_return(df: DataFrame, keys: list[str], order: list[str], keep: list[str]) -> DataFrame:
    """The earliest shot of each pixel by min_by over a total order: one hash aggregate, no sort of the group."""
    least = F.min(F.struct(*order, *keep)).alias("_m")
    return df.groupBy(*keys).agg(least).select(*keys, *(F.col(f"_m.{c}").alias(c) for c in keep))


def subsample_rows(df: DataFrame, step: int = 2, phase: int = 0) -> DataFrame:
    """Every step-th laser row, numbered anew."""
    return df.where(F.col("row") % step == phase).withColumn("row", F.floor(F.col("row") / step).cast("int"))


def pixels(df: DataFrame, frame: Column, row: Column, col: Column, value: Column, *more: Column) -> DataFrame:
    return df.select(frame.cast("long").alias("frame_id"), row.cast("int").alias("row"), col.cast("int").alias("col"), value.cast("double").alias("range"), *more)


def part_img(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = F.col("p_partkey")
    return pixels(table(spark, sf_dir, "part"), F.lit(0), F.floor(k / 50), k % 50, (F.col("p_retailprice") - 900) * F.lit(0.7) + 1)


def lineitem_img(spark: SparkSession, sf_dir: str) -> DataFrame:
    """With intensity and elongation; the first return by ship date, part and supplier."""
    k = F.col("l_orderkey")
    shots = pixels(table(spark, sf_dir, "lineitem"), F.floor(k / 1000), F.col("l_linenumber") - 1, k % 1000, F.col("l_extendedprice") / 1500, (F.col("l_discount") * 10).alias("intensity"), (F.col("l_tax") * 10).alias("elongation"), "l_shipdate", "l_partkey", "l_suppkey")
    return first_return(shots, ["frame_id", "row", "col"], ["l_shipdate", "l_partkey", "l_suppkey"], ["range", "intensity", "elongation"])


def events_img(spark: SparkSession, sf_dir: str, cropped: bool = True) -> DataFrame:
    ts = F.col("ts")
    second = F.hour(ts) * 3600 + F.minute(ts) * 60 + F.floor(F.second(ts))
    shots = pixels(table(spark, sf_dir, "events"), F.datediff(ts, F.lit("2024-01-01").cast("date")), F.col("user_id") % 16, F.floor(second / 1800), F.col("value"), "ts", "event_id")
    got = first_return(shots, ["frame_id", "row", "col"], ["ts", "event_id"], ["range"])
    return crop(got) if cropped else got


def embedding_img(spark: SparkSession, sf_dir: str) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("label").orderBy("vec_id")) - 1
    e = table(spark, sf_dir, "embeddings").withColumn("col", rank).select("label", "col", F.posexplode("embedding").alias("row", "x"))
    return pixels(e, F.col("label"), F.col("row"), F.col("col"), (F.col("x").cast("double") + 1) * F.lit(37.5))


def orders_img(spark: SparkSession, sf_dir: str) -> DataFrame:
    day = F.datediff("o_orderdate", F.lit("1995-01-01").cast("date"))
    frame = F.when(F.col("o_orderstatus") == "F", 0).when(F.col("o_orderstatus") == "O", 1).otherwise(2)
    shots = pixels(table(spark, sf_dir, "orders"), frame, F.pmod(day, F.lit(7)), F.floor(day / 7), F.col("o_totalprice") / 7000, "o_orderkey")
    return crop(first_return(shots, ["frame_id", "row", "col"], ["o_orderkey"], ["range"]))


def conversation_img(spark: SparkSession, sf_dir: str) -> DataFrame:
    return crop(pixels(table(spark, sf_dir, "conversations"), F.lit(0), F.col("turn"), F.col("conv_id"), F.length("text") % 75))


def mask_img(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, labels = table(spark, sf_dir, "documents").select("doc_id"), table(spark, sf_dir, "labels").select("doc_id")
    return pixels(d.join(labels, "doc_id", "left_semi"), F.lit(0), F.floor(F.col("doc_id") / 50), F.col("doc_id") % 50, F.lit(1.0))


def scene(spark: SparkSession, sf_dir: str, frames: int = 4, columns: int = 240, label: bool = False) -> DataFrame:
    """Closed-form ray casting: 25 beams of `nation`, spheres of `supplier`, a ground plane; the sensor moves 1 m a frame.

    Directions are rational, so that other engines get the same doubles. Obstacles are bounded (s_suppkey < 100) and broadcast."""
    r, c = F.col("row").cast("double"), F.col("col")
    te = F.lit(0.04) - F.lit(0.26) * r * r / F.lit(576.0)
    ta = F.lit(2.0) * ((c % 60).cast("double") + F.lit(0.5)) / F.lit(60.0) - F.lit(1.0)
    grid = (
        table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("int").alias("row"))
        .withColumn("col", F.explode(F.sequence(F.lit(0), F.lit(columns - 1)))).withColumn("frame_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(frames - 1).cast("long"))))
        .withColumn("te", te).withColumn("ta", ta)
        .withColumn("ux", (F.lit(1.0) - F.col("ta") * F.col("ta")) / (F.lit(1.0) + F.col("ta") * F.col("ta"))).withColumn("uy", F.lit(2.0) * F.col("ta") / (F.lit(1.0) + F.col("ta") * F.col("ta")))
        .withColumn("hs", (F.lit(1.0) - F.col("te") * F.col("te")) / (F.lit(1.0) + F.col("te") * F.col("te"))).withColumn("dz", F.lit(2.0) * F.col("te") / (F.lit(1.0) + F.col("te") * F.col("te")))
    )
    q = F.floor(c / 60)
    turn = lambda a, b, d, e: F.when(q == 0, a).when(q == 1, b).when(q == 2, d).otherwise(e)
    ux, uy = F.col("ux"), F.col("uy")
    grid = grid.withColumn("dx", turn(ux, -uy, -ux, uy) * F.col("hs")).withColumn("dy", turn(uy, ux, -uy, -ux) * F.col("hs")).select("frame_id", "row", "col", "dx", "dy", "dz")
    k = F.col("s_suppkey")
    spheres = table(spark, sf_dir, "supplier").where(k < 100).select(((k * 37) % 121 - 60).cast("double").alias("cx"), ((k * 53 + 29) % 121 - 60).cast("double").alias("cy"), (F.lit(0.5) + F.lit(2.0) * F.col("s_nationkey").cast("double") / F.lit(24.0)).alias("rad"))
    ox = F.col("frame_id").cast("double") - F.col("cx")
    b = ox * F.col("dx") + (-F.col("cy")) * F.col("dy")
    cc = ox * ox + F.col("cy") * F.col("cy") - F.col("rad") * F.col("rad")
    hits = grid.crossJoin(F.broadcast(spheres)).withColumn("b", b).withColumn("cc", cc).where((F.col("cc") > 0) & (F.col("b") < 0) & (F.col("b") * F.col("b") - F.col("cc") >= 0))
    near = hits.groupBy("frame_id", "row", "col").agg(F.min(-F.col("b") - F.sqrt(F.col("b") * F.col("b") - F.col("cc"))).alias("t"))
    ground = F.when(F.col("dz") < 0, F.lit(-2.0) / F.col("dz"))
    out = grid.join(near, ["frame_id", "row", "col"], "left").withColumn("range", F.least("t", ground)).withColumn("hit", (F.col("t").isNotNull() & (F.col("range") == F.col("t"))))
    return crop(out).select("frame_id", "row", "col", "range", *(["hit", "dx", "dy", "dz"] if label else []))


IMAGES = {"scene": scene, "part": part_img, "lineitem": lineitem_img, "events": events_img, "embedding": embedding_img, "orders": orders_img, "conversation": conversation_img, "mask": mask_img}

#: The same images in DuckDB SQL: relations with frame_id, row, col, range.
SQL = {
    "part": "SELECT 0::BIGINT AS frame_id, (p_partkey // 50)::INT AS row, (p_partkey % 50)::INT AS col, (p_retailprice - 900) * 7e-1 + 1 AS range FROM part",
    "lineitem": "SELECT (l_orderkey // 1000)::BIGINT AS frame_id, (l_linenumber - 1)::INT AS row, (l_orderkey % 1000)::INT AS col, l_extendedprice / 1500 AS range, l_discount * 10 AS intensity, l_tax * 10 AS elongation FROM lineitem QUALIFY row_number() OVER (PARTITION BY l_orderkey, l_linenumber ORDER BY l_shipdate, l_partkey, l_suppkey) = 1",
    "events": "SELECT * FROM (SELECT date_diff('day', DATE '2024-01-01', ts::DATE)::BIGINT AS frame_id, (user_id % 16)::INT AS row, ((hour(ts) * 3600 + minute(ts) * 60 + second(ts)) // 1800)::INT AS col, value AS range FROM events QUALIFY row_number() OVER (PARTITION BY frame_id, row, col ORDER BY ts, event_id) = 1) WHERE range > 0 AND range <= 75",
    "embedding": "SELECT label::BIGINT AS frame_id, (i - 1)::INT AS row, col::INT AS col, (embedding[i]::DOUBLE + 1) * 375e-1 AS range FROM (SELECT label, embedding, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS col, unnest(generate_series(1, 64)) AS i FROM embeddings)",
    "orders": "SELECT * FROM (SELECT CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END::BIGINT AS frame_id, (((d % 7) + 7) % 7)::INT AS row, floor(d / 7)::INT AS col, o_totalprice / 7000 AS range FROM (SELECT *, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS d FROM orders) QUALIFY row_number() OVER (PARTITION BY frame_id, row, col ORDER BY o_orderkey) = 1) WHERE range > 0 AND range <= 75",
    "conversation": "SELECT * FROM (SELECT 0::BIGINT AS frame_id, turn::INT AS row, conv_id::INT AS col, (length(text) % 75)::DOUBLE AS range FROM conversations) WHERE range > 0",
    "mask": "SELECT 0::BIGINT AS frame_id, (doc_id // 50)::INT AS row, (doc_id % 50)::INT AS col, 1e0 AS range FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)",
    "scene": """SELECT frame_id, row, col, range FROM (
        SELECT g.frame_id, g.row, g.col, least(min(t), min(CASE WHEN dz < 0 THEN -2e0 / dz END)) AS range FROM (
            SELECT *, hx * hs AS dx, hy * hs AS dy FROM (
                SELECT frame_id, row, col, (1e0 - te * te) / (1e0 + te * te) AS hs, 2e0 * te / (1e0 + te * te) AS dz,
                    CASE col // 60 WHEN 0 THEN ux WHEN 1 THEN -uy WHEN 2 THEN -ux ELSE uy END AS hx, CASE col // 60 WHEN 0 THEN uy WHEN 1 THEN ux WHEN 2 THEN -uy ELSE -ux END AS hy
                FROM (SELECT *, (1e0 - ta * ta) / (1e0 + ta * ta) AS ux, 2e0 * ta / (1e0 + ta * ta) AS uy FROM (
                    SELECT f::BIGINT AS frame_id, n_nationkey::INT AS row, c::INT AS col, 4e-2 - 26e-2 * n_nationkey::DOUBLE * n_nationkey::DOUBLE / 576e0 AS te, 2e0 * ((c % 60)::DOUBLE + 5e-1) / 60e0 - 1e0 AS ta
                    FROM nation, generate_series(0, 239) a(c), generate_series(0, 3) b(f))))) g
        LEFT JOIN (SELECT cx, cy, rad FROM (SELECT ((s_suppkey * 37) % 121 - 60)::DOUBLE AS cx, ((s_suppkey * 53 + 29) % 121 - 60)::DOUBLE AS cy, 5e-1 + 2e0 * s_nationkey::DOUBLE / 24e0 AS rad FROM supplier WHERE s_suppkey < 100)) s ON true
        LEFT JOIN LATERAL (SELECT CASE WHEN cc > 0 AND b < 0 AND b * b - cc >= 0 THEN -b - sqrt(b * b - cc) END AS t FROM (SELECT (frame_id - cx) * dx + (-cy) * dy AS b, (frame_id - cx) * (frame_id - cx) + cy * cy - rad * rad AS cc)) h ON true
        GROUP BY g.frame_id, g.row, g.col) WHERE range > 0 AND range <= 75""",
}
