"""Functions for SQL users: might_hold per filter, a filter aggregate, table functions for grams and footprints."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from . import kernels as K
from .geometry import WORDS, FilterSpec
from .probe import answers, as_array


def register_filter(spark: SparkSession, name: str, lines: DataFrame, spec: FilterSpec) -> None:
    """SQL function ``name(key)``: may the filter hold the key (null for null)?"""
    shared = spark.sparkContext.broadcast(as_array(lines, spec))

    @pandas_udf("boolean")
    def might_hold(keys: pd.Series) -> pd.Series:
        found, _, _ = answers(shared.value, keys.fillna(0).to_numpy(np.int64), spec)
        return pd.Series(found).astype("boolean").mask(keys.isna().to_numpy())

    spark.udf.register(name, might_hold)


def register_aggregate(spark: SparkSession, name: str, spec: FilterSpec) -> None:
    """SQL aggregate ``name(key)``: the packed lines of a small filter per group (one shard)."""

    @pandas_udf("binary")
    def filter_of(keys: pd.Series) -> bytes:
        x = K.prepared(keys.dropna().to_numpy(np.int64), spec)
        lines = np.zeros((spec.lines, WORDS), np.uint64)
        K.insert(lines, K.candidates(x, spec), K.footprints(x, spec), spec)
        return lines.astype(">u8").tobytes()

    spark.udf.register(name, filter_of)


def register_tables(spark: SparkSession, spec: FilterSpec) -> None:
    """SQL table functions ``qgram_table(letters, q)`` and ``footprint_table(key)``."""

    @udtf(returnType="pos int, gram long")
    class QgramTable:
        def eval(self, letters: str, q: int):
            for i in range(len(letters or "") - q + 1):
                yield i + 1, int(letters[i : i + q], 4)

    @udtf(returnType="i int, address int")
    class FootprintTable:
        def eval(self, key: int):
            if key is not None:
                for i, a in enumerate(K.addresses(K.prepared(np.array([key], np.int64), spec), spec)[0]):
                    yield i, int(a)

    spark.udtf.register("qgram_table", QgramTable)
    spark.udtf.register("footprint_table", FootprintTable)
