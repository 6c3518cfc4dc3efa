"""What the schemes offer to SQL: views of their tables, scalar and table functions."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from enctopics.functions.crypto import mac_pads


def register(spark: SparkSession, key: str, **views: DataFrame) -> None:
    """Views by name, and the functions token_handle(tok), under key, and tokens_of(text)."""
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    inner, outer = (x.hex() for x in mac_pads(key))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION token_handle(tok STRING) RETURNS STRING RETURN sha2(concat(X'{outer}', unhex(sha2(concat(X'{inner}', cast(tok AS BINARY)), 256))), 256)")
    spark.udtf.register("tokens_of", token_udtf)


@udtf(returnType=T.StructType([T.StructField("tok", T.StringType()), T.StructField("pos", T.IntegerType())]))
class token_udtf:  # noqa: N801  a table function
    def eval(self, text: str) -> Iterator[tuple[str, int]]:
        for i, m in enumerate(re.finditer(r"[^\W\d_]{3,}", (text or "").lower())):
            yield m[0], i


@pandas_udf(T.DoubleType())
def cosine_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    """The batched twin of the expression in operators.vectors."""
    import numpy as np

    x, y = np.stack(a.to_list()).astype(float), np.stack(b.to_list()).astype(float)
    return pd.Series((x * y).sum(axis=1) / np.linalg.norm(x, axis=1) / np.linalg.norm(y, axis=1))


@pandas_udf(T.DoubleType())
def coherency_udf(v: pd.Series) -> float:
    """Mean cosine of a group's vectors; the grouped twin of metrics.coherency."""
    import numpy as np

    x = np.stack(v.to_list()).astype(float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    p = len(x)
    return float("nan") if p < 2 else float(((x.sum(axis=0) ** 2).sum() - p) / (p * (p - 1)))
