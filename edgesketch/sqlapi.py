"""The SQL surface: scalar functions, table functions and the synthetic data source."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from edgesketch.functions.sampler import STATUS, SamplerKernel, SketchParams
from edgesketch.sources.io import SyntheticGraph


def register(spark: SparkSession, params: SketchParams | None = None) -> None:
    """Registers ``edge_id``, ``decode_body``, ``xor_body``, ``xor_agg``, ``union_find`` and the data source."""
    spark.dataSource.register(SyntheticGraph)
    p = (params or SketchParams(1 << 20)).with_(copies=1)

    @F.pandas_udf("status string, eid long")
    def decode_body(body: pd.Series) -> pd.DataFrame:
        status, eid = SamplerKernel(p).decode(np.frombuffer(b"".join(body), np.uint64).reshape(len(body), -1))
        return pd.DataFrame({"status": [STATUS[int(s)] for s in status], "eid": eid.astype(np.int64)})

    @F.pandas_udf("binary")
    def xor_body(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([(np.frombuffer(x, np.uint64) ^ np.frombuffer(y, np.uint64)).tobytes() for x, y in zip(a, b)])

    @F.pandas_udf("binary")
    def xor_agg(body: pd.Series) -> bytes:
        return np.bitwise_xor.reduce(np.frombuffer(b"".join(body), np.uint64).reshape(len(body), -1), axis=0).tobytes()

    @F.udtf(returnType="vertex: long, component: long")
    class UnionFindTable:
        """Components within one partition of (u, v) rows: a local contraction before the shuffle."""

        def __init__(self):
            self.parent = {}

        def _find(self, x):
            while self.parent.setdefault(x, x) != x:
                self.parent[x] = self.parent[self.parent[x]]
                x = self.parent[x]
            return x

        def eval(self, row):
            a, b = self._find(row["u"]), self._find(row["v"])
            if a != b:
                self.parent[max(a, b)] = min(a, b)

        def terminate(self):
            for x in list(self.parent):
                yield x, self._find(x)

    for name, f in (("decode_body", decode_body), ("xor_body", xor_body), ("xor_agg", xor_agg)):
        spark.udf.register(name, f)
    spark.udtf.register("union_find", UnionFindTable)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edge_id(u BIGINT, v BIGINT) RETURNS BIGINT RETURN shiftleft(least(u, v), 32) | greatest(u, v)")
