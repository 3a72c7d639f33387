"""What SQL functions cannot express: a sketch as an aggregate, noisy copies and bands as table functions."""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from fuzzcount.functions.bloom import ELL, LANE, LANES
from fuzzcount.functions.digest import below


def _type(*fields: tuple) -> StructType:
    return StructType([StructField(name, kind) for name, kind in fields])


def draw(text: str) -> int:
    """The number that `digest.num` draws from a text."""
    return int(hashlib.md5(text.encode()).hexdigest()[:8], 16)


def _lowest_bits(values: pd.Series) -> np.ndarray:
    drawn = np.array([draw(str(v)) for v in values.dropna().unique()], np.int64)
    return np.where(drawn == 0, np.int64(1) << 32, drawn & -drawn)


@F.pandas_udf(LongType())
def fm_bitmap(values: pd.Series) -> int:
    """One bitmap of a Flajolet-Martin sketch: the lowest set bits of the values' digests, or-ed."""
    return int(np.bitwise_or.reduce(_lowest_bits(values), initial=np.int64(0)))


@F.udtf(returnType=_type(("dum_no", IntegerType()), *((w, LongType()) for w in LANES)))
class NoisyCopies:
    """Copies of a filter with each bit flipped with a probability; the draws are those of `decoys.dummies`."""

    def eval(self, w0: int, w1: int, w2: int, w3: int, copies: int, p_flip: float, key: str, ref_id: int):
        bound = below(p_flip)
        for n in range(copies):
            lanes = [w0, w1, w2, w3]
            for b in range(ELL):
                if draw(f"{key}|dum|{ref_id}|{n}|{b}") < bound:
                    lanes[b // LANE] ^= 1 << b % LANE
            yield (n, *lanes)


@F.udtf(returnType=_type(("band", IntegerType()), ("value", LongType())))
class LaneBands:
    """Bit samples of a filter, as `linkage.bands` takes them."""

    def eval(self, w0: int, w1: int, w2: int, w3: int, width: int):
        per_lane = LANE // width
        for i, lane in enumerate((w0, w1, w2, w3)):
            for j in range(per_lane):
                yield i * per_lane + j, (lane >> j * width) & (2**width - 1)


def register(spark: SparkSession) -> None:
    """Make them SQL functions of the session: fc_fm(x), and fc_noisy_copies and fc_bands for lateral joins."""
    spark.udf.register("fc_fm", fm_bitmap)
    spark.udtf.register("fc_noisy_copies", NoisyCopies)
    spark.udtf.register("fc_bands", LaneBands)
