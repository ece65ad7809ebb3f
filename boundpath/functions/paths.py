"""Arrow-batched kernels over paths."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame


def path_pairs(paths: DataFrame) -> DataFrame:
    """(req_id, pos, a, b): a row for each link of each path, from (req_id, path); null and one-vertex paths have none."""

    def run(batches):
        for batch in batches:
            column = batch.column(1).fill_null([])
            sizes = np.diff(column.offsets.to_numpy())
            values = column.values.to_numpy(zero_copy_only=False)[column.offsets[0].as_py() :]
            owner = np.repeat(np.arange(len(sizes)), sizes)
            pos = np.arange(len(values)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
            inner = np.flatnonzero(owner[1:] == owner[:-1])
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(owner[inner])), pa.array(pos[inner].astype(np.int32)), pa.array(values[inner]), pa.array(values[inner + 1])], names=["req_id", "pos", "a", "b"])

    return paths.mapInArrow(run, "req_id bigint, pos int, a bigint, b bigint")


def path_udtf():
    """A table function for SQL: the links of one path as (pos, a, b)."""
    from pyspark.sql.functions import udtf

    class Steps:
        def eval(self, path):
            known = path or []
            for pos in range(len(known) - 1):
                yield pos, known[pos], known[pos + 1]

    return udtf(Steps, returnType="pos int, a bigint, b bigint")
