"""A loss's value and derivatives as columns of a table of scores."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.types import DoubleType, StructField, StructType

from ..functions.losses import Loss


def derivatives(scored: DataFrame, loss: Loss, scores: list[str], targets: str | list[str], keep: list[str]) -> DataFrame:
    """(keep, g0.., h0.., loss) of every row: gradient, diagonal curvature and value. targets: a label column, or one for each score."""
    c, several = len(scores), not isinstance(targets, str)
    extra = [f"g{k}" for k in range(c)] + [f"h{k}" for k in range(c)] + ["loss"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            num = lambda n: b.column(n).to_numpy(zero_copy_only=False)  # noqa: B023, E731
            s = np.stack([num(n) for n in scores], axis=1).astype(float)
            y = np.stack([num(n) for n in targets], axis=1).astype(float) if several else num(targets)
            made = [*loss.grad(s, y).T, *loss.diag(s, y).T, loss.value(s, y)]
            yield pa.RecordBatch.from_arrays([*(b.column(n) for n in keep), *(pa.array(np.ascontiguousarray(v, np.float64)) for v in made)], [*keep, *extra])

    asked = list(dict.fromkeys([*keep, *scores, *(targets if several else [targets])]))
    fields = [f for f in scored.select(*keep).schema.fields] + [StructField(n, DoubleType()) for n in extra]
    return scored.select(*asked).mapInArrow(run, StructType(fields))
