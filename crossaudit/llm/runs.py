"""Runs of equal keys in a sorted stream of Arrow batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa


def whole_runs(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Batches cut between keys, with the starts and lengths of their runs. The rows of a run must be bounded by the caller."""

    def heads(batch: pa.RecordBatch) -> np.ndarray:
        new = np.ones(batch.num_rows, bool)
        cols = [batch.column(k).to_numpy(zero_copy_only=False) for k in keys]
        new[1:] = np.any([c[1:] != c[:-1] for c in cols], axis=0)
        return np.flatnonzero(new)

    rest: pa.RecordBatch | None = None
    for b in batches:
        if not b.num_rows:
            continue
        whole = b if rest is None else pa.Table.from_batches([rest, b]).combine_chunks().to_batches()[0]
        starts = heads(whole)
        cut = int(starts[-1])
        if cut:
            yield whole.slice(0, cut), starts[:-1], np.diff(starts)
        rest = whole.slice(cut)
    if rest is not None:
        yield rest, np.zeros(1, np.int64), np.array([rest.num_rows])
