"""Functions that Spark lacks and columns cannot express well: a table function and a grouped aggregate."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


@F.udtf(returnType="gram string")
class Ngrams:
    """Rows of the n-grams of a text whose words are joined by single spaces."""

    def eval(self, text: str, n: int):
        w = text.split(" ") if text else []
        for i in range(len(w) - n + 1):
            yield (" ".join(w[i : i + n]),)


@F.pandas_udf(DoubleType())
def soft_mean(value: pd.Series, weight: pd.Series) -> float:
    """The mean of values weighted by the softmax of ``weight``."""
    e = np.exp(weight - weight.max())
    return float((e * value).sum() / e.sum())
