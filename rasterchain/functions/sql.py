"""Functions for SQL: one filter of a row, a chain over pixels, spectra as an aggregate, an operator by name."""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, IntegerType, LongType, StructField, StructType

from rasterchain import kernels as K
from rasterchain.chain import Chain, run

# types, not strings: those are parsed by a session, which may not run yet
LONGS = ArrayType(LongType())
PIXEL = StructType([StructField("img", LongType()), StructField("y", IntegerType()), StructField("x", IntegerType()), StructField("v", LongType())])
OFFSET = StructType([StructField("dy", IntegerType()), StructField("dx", IntegerType())])


@pandas_udf(LONGS)
def rc_row_min3(rows: pd.Series) -> pd.Series:
    """The horizontal filter of a row."""
    return rows.map(lambda r: None if r is None else K.row3(np.asarray(r, np.int64), K.MIN, -1))


@pandas_udf(LONGS)
def rc_granulometry(y: pd.Series, x: pd.Series, v: pd.Series, s_max: pd.Series) -> list:
    """Aggregate over the pixels of an image: sums of openings of sizes 0 to s_max."""
    a = np.zeros((int(y.max()) + 1, int(x.max()) + 1), np.int64)
    a[y.to_numpy(), x.to_numpy()] = v.to_numpy()
    return K.granulometry(a, int(s_max.iloc[0]))


@udtf(returnType=PIXEL)
class RcChain:
    """rc_chain(chain, TABLE(pixels) PARTITION BY img): runs a chain, given as JSON, on each image."""

    def __init__(self):
        self.rows, self.spec = [], None

    def eval(self, spec: str, row):
        self.rows.append((row["img"], row["y"], row["x"], row["v"]))
        self.spec = spec

    def terminate(self):
        if not self.rows:
            return
        img = self.rows[0][0]
        y, x, v = (np.array(c) for c in zip(*(r[1:] for r in self.rows), strict=True))
        a = np.zeros((y.max() + 1, x.max() + 1), np.int64)
        a[y, x] = v
        out = run(a, Chain.from_json(self.spec))
        for (j, i), value in np.ndenumerate(out):
            yield img, int(j), int(i), int(value)


@udtf(returnType=OFFSET)
class RcOffsets:
    """rc_offsets(s): the places of the square of side 2s + 1."""

    def eval(self, s: int):
        for dy in range(-s, s + 1):
            for dx in range(-s, s + 1):
                yield dy, dx


def register_sql(spark: SparkSession) -> None:
    """Makes rc_row_min3, rc_granulometry, rc_chain and rc_offsets known to SQL of this session."""
    spark.udf.register("rc_row_min3", rc_row_min3)
    spark.udf.register("rc_granulometry", rc_granulometry)
    spark.udtf.register("rc_chain", RcChain)
    spark.udtf.register("rc_offsets", RcOffsets)


def chain_json(chain: Chain) -> str:
    return json.dumps(json.loads(chain.to_json()))


def spectrum_map(spectrum):
    """(img, s, ps) -> (img, spectrum map<int, bigint>)."""
    return spectrum.groupBy("img").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("s", "ps")))).alias("spectrum"))
