"""Vector arithmetic on array columns: expressions first, Arrow UDFs where a user wants them."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import ensure_importable


def dot(a: str | Column, b: str | Column) -> Column:
    product = F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double"))
    return F.aggregate(product, F.lit(0.0), lambda s, x: s + x)


def norm(a: str | Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: str | Column, b: str | Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def l2(a: str | Column, b: str | Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x))


def l2_normalize(spark: SparkSession):
    """Arrow UDF: arrays scaled to unit length."""
    import pandas as pd

    ensure_importable(spark)

    def normalized(column):
        import numpy as np

        x = np.array(column.tolist(), float)
        return pd.Series(list(x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-30)))

    normalized.__annotations__ = {"column": pd.Series, "return": pd.Series}
    return F.pandas_udf(normalized, "array<double>")


def vector_mean(spark: SparkSession):
    """Grouped-aggregate Arrow UDF: mean vector. Without partial aggregation; `operators.features` has the form for scale."""
    import pandas as pd

    ensure_importable(spark)

    def mean(column):
        import numpy as np

        return np.array(column.tolist(), float).mean(axis=0).tolist()

    mean.__annotations__ = {"column": pd.Series, "return": list[float]}
    return F.pandas_udf(mean, "array<double>", F.PandasUDFType.GROUPED_AGG)
