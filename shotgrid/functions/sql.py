"""Functions for SQL users: register(spark), then sg_* in queries."""

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..operators import codec, coders, masks
from .shipping import ship


def functions() -> dict:
    """Arrow-batched functions: whole columns go to Python at once."""

    @F.pandas_udf("binary")
    def sg_encode_bytes(v: pd.Series) -> pd.Series:
        """Residuals as the bytes of the shortest coder, its number in front."""
        kinds = list(coders.CODERS)
        made = (coders.smallest(np.asarray(x, np.int64)) for x in v)
        return pd.Series([bytes([kinds.index(n)]) + body for n, body in made])

    @F.pandas_udf("array<bigint>")
    def sg_decode_bytes(v: pd.Series) -> pd.Series:
        kinds = list(coders.CODERS.values())
        return pd.Series([kinds[x[0]][1](bytes(x[1:])) for x in v])

    @F.pandas_udf("binary")
    def sg_varint(v: pd.Series) -> pd.Series:
        return pd.Series([coders.varints(coders.zigzag(np.asarray(x, np.int64))) for x in v])

    @F.pandas_udf("binary")
    def sg_mask_pack(v: pd.Series) -> pd.Series:
        """A row of booleans as the shortest mask."""
        return pd.Series([masks.encode(np.asarray(x, bool)[None, :]) for x in v])

    @F.pandas_udf("double")
    def sg_h0(v: pd.Series) -> float:
        """Order-0 entropy in bits: an aggregate over groups that fit one task."""
        n = np.unique(v.to_numpy(), return_counts=True)[1]
        return float(-(n / n.sum() * np.log2(n / n.sum())).sum()) if len(n) else 0.0

    return {"sg_encode_bytes": sg_encode_bytes, "sg_decode_bytes": sg_decode_bytes, "sg_varint": sg_varint, "sg_mask_pack": sg_mask_pack, "sg_h0": sg_h0}


class Decoded:
    """sg_decode(TABLE(container)): the pixels of container rows. Filters on its output don't reach its input: filter the container."""

    def eval(self, row):
        for x in codec.decode_rows([row.asDict()]).to_pylist():
            yield x["frame_id"], x["row"], x["col"], x["code"], x["range"]


def register(spark: SparkSession) -> None:
    """Makes the functions and the table function known to spark.sql."""
    ship(spark)
    for name, f in functions().items():
        spark.udf.register(name, f)
    spark.udtf.register("sg_decode", F.udtf(Decoded, returnType=codec.PIXELS))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sg_code(v DOUBLE, d DOUBLE) RETURNS BIGINT RETURN CAST(floor(v / d + 0.5D) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sg_zigzag(v BIGINT) RETURNS BIGINT RETURN shiftleft(v, 1) ^ shiftright(v, 63)")


def arrow_schema() -> pa.Schema:
    """The container's schema for writers outside Spark."""
    return pa.schema(list(zip(codec.NAMES, codec.TYPES)))
