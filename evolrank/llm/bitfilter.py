"""A fixed-size bit filter over ids, built by a distributed aggregate.

It answers "is this id surely absent?" on the scan side of a join, so that rows
without a partner stay out of the shuffle.  Its size does not depend on the
data: a crowded filter lets more rows through but never loses one.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FILTER_BITS = 1 << 25  # 4 MB


def _place(c: Column) -> Column:
    return F.pmod(F.xxhash64(c), F.lit(FILTER_BITS))


def bit_filter(ids: DataFrame) -> Callable[[Column], Column]:
    """A function from an id column to a boolean column: may the id be in the one-column table ``ids``?"""
    place = _place(ids[ids.columns[0]])
    parts = ids.select(place.alias("p")).groupBy(F.floor(F.col("p") / 32768).alias("k")).agg(F.bitmap_construct_agg(F.col("p") % 32768).alias("bits"))
    wide = np.zeros(FILTER_BITS // 8, dtype=np.uint8)
    for r in parts.collect():  # at most FILTER_BITS / 32768 rows of 4 kB, in one job (an iterator would run one for each partition)
        wide[r.k * 4096 : (r.k + 1) * 4096] = np.frombuffer(bytes(r.bits), dtype=np.uint8)
    held = ids.sparkSession.sparkContext.broadcast(wide)

    @F.pandas_udf("boolean")
    def may_hold(p: pd.Series) -> pd.Series:
        at = p.to_numpy()
        return pd.Series((held.value[at >> 3] >> (at & 7)) & 1 == 1)

    return lambda c: may_hold(_place(c))
