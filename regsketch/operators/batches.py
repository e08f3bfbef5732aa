"""Estimates of very many sketches in Arrow batches.

Expressions in the JVM are best for a few thousand value-count vectors: they need no Python process and fuse with what makes the vectors.
For millions of vectors numpy works on all of a batch at once and takes about a microsecond for each.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from ..functions.numeric import corrected_raw_many, ml_many
from ..plans.ship import map_arrow

METHODS = ("corrected_raw", "ml")


def estimates(r3: DataFrame, methods: tuple[str, ...] = METHODS, epsilon: float = 1e-2) -> DataFrame:
    """The columns of R3 but for counts, and one for each method. All vectors are of one spec; an empty table gives no rows."""
    keys = [c for c in r3.columns if c != "counts"]
    if unknown := set(methods) - set(METHODS):
        raise ValueError(f"no batch form of {', '.join(sorted(unknown))}; there are {', '.join(METHODS)}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            counts = batch.column("counts").flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            found = [pa.array(corrected_raw_many(counts) if m == "corrected_raw" else ml_many(counts, epsilon)[0]) for m in methods]
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keys), *found], names=[*keys, *methods])

    schema = ", ".join([*(f"`{k}` {r3.schema[k].dataType.simpleString()}" for k in keys), *(f"`{m}` double" for m in methods)])
    return map_arrow(r3, run, schema)
