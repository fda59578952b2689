"""Python user functions; each has a native twin, which is the default in the engine."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


@F.pandas_udf(DoubleType())
def relative_change(a: pd.Series, b: pd.Series) -> pd.Series:
    """|a - b| / max(a, b)."""
    return (a - b).abs() / a.where(a > b, b)


@F.pandas_udf(DoubleType())
def euclidean(x: pd.Series) -> float:
    """Euclidean norm of a group."""
    return float((x * x).sum() ** 0.5)


class NeighbourPairs:
    """(pair) for every two words that follow each other in a text."""

    def eval(self, text: str):
        words = (text or "").split(" ")
        for a, b in zip(words, words[1:], strict=False):
            yield (f"{a} {b}",)


def block_sums(blocks):
    """(v, total) of each block of (v, out_deg): the shares that reach a vertex, summed within the block."""
    for block in blocks:
        total = (1.0 / block["out_deg"]).groupby(block["v"]).sum()
        yield total.rename("total").rename_axis("v").reset_index()
