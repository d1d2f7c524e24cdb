"""User functions over the index: a vectorised UDF that encodes, a table function that probes."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F


def encoder(index):
    """A vectorised UDF from a raw vector to its codes as ARRAY<INT>; it normalises by itself.

    Spark does not extract Python functions whose argument holds a lambda, so give it a plain column.
    """

    @F.pandas_udf("array<int>")
    def encode(v: pd.Series) -> pd.Series:
        x = np.stack(v.to_numpy()).astype(np.float64) if len(v) else np.zeros((0, index.d))
        _, _, code, _, _ = index.quantize(x / np.sqrt((x * x).sum(axis=1, keepdims=True)))
        return pd.Series(list(code.astype(np.int32)))

    return encode


def prober(index, n_p: int):
    """A table function from a query vector to its n_p cells."""

    @F.udtf(returnType="cell long, rank long, ip double")
    class Probe:
        def eval(self, v: list):
            s = np.asarray(v, float) @ index.c.T
            for r, c in enumerate(np.argsort(-s, kind="stable")[:n_p]):
                yield int(c), r + 1, float(s[c])

    return Probe
