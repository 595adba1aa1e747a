"""Functions on sketches: expressions first, pandas where an aggregate is missing, a table function for SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf


def top_frequency(sketch: str | Column) -> Column:
    """Largest count of an array of (n, value)."""
    return F.aggregate(sketch, F.lit(0).cast("long"), lambda acc, h: F.greatest(acc, h["n"]))


def _kmv(hashes: pd.Series) -> float:
    kept = np.unique(hashes.to_numpy(np.int64))
    if len(kept) < 128:
        return float(len(kept))
    return 127 * 2.0**64 / (float(kept[127]) + 2.0**63)


def kmv_distinct(hashes: Column) -> Column:
    """Distinct estimate from the 128 smallest of a group's 64-bit hashes, as a grouped pandas aggregate."""
    return pandas_udf(_kmv, "double")(hashes)


@udtf(returnType="value string, n bigint")
class SketchExplode:
    """Rows of a stored dictionary sketch."""

    def eval(self, sketch):
        for item in sketch or ():
            yield item["value"], item["n"]
