"""range_knn(path, qvec, lo, hi, k): range search as a table function, for SQL with LATERAL.

A table function sees no DataFrame, so it opens the saved index itself and keeps shards per worker:
meant for few queries or small indexes; the batch search is the way for many.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

COLUMNS = ["shard", "ids", "attrs", "vecs", "start", "nbrs", "closer"]


class RangeKnn:
    """Shards are read when a query meets them, at most ``keep`` of them are held."""

    keep = 8
    ef = 64

    def __init__(self) -> None:
        self.opened: dict[str, tuple] = {}
        self.held: dict[tuple[str, int], object] = {}

    def _dataset(self, path: str):
        if path not in self.opened:
            import pyarrow.dataset as ds
            from pyarrow import fs

            store, at = fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (None, path)
            data = ds.dataset(at, filesystem=store, format="parquet")
            ends = data.to_table(columns=["shard", "lo", "hi"]).to_pylist()
            self.opened[path] = (data, ends)
        return self.opened[path]

    def _shard(self, path: str, number: int):
        import pyarrow.dataset as ds

        from rangeknn.operators.index import Shard

        if (path, number) not in self.held:
            if len(self.held) >= self.keep:
                self.held.pop(next(iter(self.held)))
            rows = self._dataset(path)[0].to_table(columns=COLUMNS, filter=ds.field("shard") == number).combine_chunks()
            self.held[path, number] = Shard(rows.to_batches()[0])
        return self.held[path, number]

    def eval(self, path: str, qvec: list, lo: float, hi: float, k: int):
        from rangeknn.operators.index import graph_kernel

        if path is None or qvec is None or k is None:
            return
        found, search = [], graph_kernel(max(self.ef, k))
        for s in self._dataset(path)[1]:
            if (lo is not None and s["hi"] < lo) or (hi is not None and s["lo"] > hi):
                continue
            shard = self._shard(path, s["shard"])
            a, b = shard.span(lo, hi)
            if a <= b:
                found += [(d, int(shard.ids[p])) for d, p in search(shard, np.array(qvec, float), a, b, k, 0)[0]]
        for n, (d, i) in enumerate(sorted(found)[:k]):
            yield n + 1, i, d


def register(spark: SparkSession, name: str = "range_knn", ef: int = 64) -> None:
    kind = type("RangeKnn", (RangeKnn,), {"ef": ef})
    spark.udtf.register(name, udtf(kind, returnType="rn int, id bigint, d2 double"))
