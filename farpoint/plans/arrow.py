"""Arrow helpers for kernels that see sorted rows as a stream of batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa


def grouped(batches: Iterator[pa.RecordBatch], key: int = 0) -> Iterator[pa.RecordBatch]:
    """Whole groups of consecutive equal keys (integers), put together across batches."""
    held: list[pa.RecordBatch] = []
    join = lambda parts: parts[0] if len(parts) == 1 else pa.Table.from_batches(parts).combine_chunks().to_batches()[0]
    for b in batches:
        if not b.num_rows:
            continue
        keys = b.column(key).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), b.num_rows]
        for a, z in zip(cuts, cuts[1:]):
            part = b.slice(a, z - a)
            if held and a == 0 and held[0].column(key)[0].as_py() == keys[0]:
                held.append(part)
                continue
            if held:
                yield join(held)
            held = [part]
    if held:
        yield join(held)


def matrix(column: pa.Array, d: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
