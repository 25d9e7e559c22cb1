"""Registration of scalar, aggregate and table functions with a session."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import IntegerType, LongType, StringType, StructField, StructType

from phrasework.kernels.suffix import SuffixIndex, codes_of
from phrasework.kernels.two_way import Options
from phrasework.operators.parse import METHODS, _phrase_rows

PHRASE_ROWS = StructType(
    [StructField("phrase_no", IntegerType()), *(StructField(c, LongType()) for c in ("start", "length", "ref")), *(StructField(c, StringType()) for c in ("literal", "side"))]
)


def _count(text: str | None, method: str) -> int | None:
    if text is None:
        return None
    codes = codes_of(text)
    return len(METHODS[method](codes, SuffixIndex(codes), Options()))


@pandas_udf(LongType())
def two_way_count(text: pd.Series) -> pd.Series:
    return text.map(lambda t: _count(t, "two_way"), na_action=None).astype("Int64")


@pandas_udf(LongType())
def lz77_count(text: pd.Series) -> pd.Series:
    return text.map(lambda t: _count(t, "lz77"), na_action=None).astype("Int64")


@pandas_udf(LongType())
def lex_count(text: pd.Series) -> pd.Series:
    return text.map(lambda t: _count(t, "lex"), na_action=None).astype("Int64")


def _table_function(method: str):
    class Phrases:
        def eval(self, text: str) -> Iterator[tuple]:
            if text is not None:
                codes = codes_of(text)
                for row in _phrase_rows("", text, METHODS[method](codes, SuffixIndex(codes), Options()), "codepoint"):
                    yield row[1:]

    return udtf(Phrases, returnType=PHRASE_ROWS)


class _SuffixRows:
    def eval(self, text: str) -> Iterator[tuple]:
        if text is not None:
            index = SuffixIndex(codes_of(text))
            yield from zip(range(1, index.n + 1), (index.sa + 1).tolist(), index.lcp.tolist())


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL under their own names."""
    for f in (two_way_count, lz77_count, lex_count):
        spark.udf.register(f.__name__, f)
    for method in ("two_way", "lz77", "lex", "lz_next"):
        spark.udtf.register(f"{method}_phrases", _table_function(method))
    spark.udtf.register("suffix_rows", udtf(_SuffixRows, returnType=StructType([StructField(c, LongType()) for c in ("rank", "pos", "lcp")])))
