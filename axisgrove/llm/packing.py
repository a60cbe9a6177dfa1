"""Whole groups from sorted batches, and bitmaps of bounded size as filters of 64-bit hashes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from axisgrove.plans.storage import cut, release

#: Bits of a filter, whatever the number of hashes. A filter never misses a hash; it may let others pass.
FILTER_BITS = 26


def whole_groups(batches, key: str):
    """Tables of whole groups from batches that are sorted by ``key``; a group is never split."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = batch.column(key).to_numpy(zero_copy_only=False)
        start = int(np.searchsorted(keys, keys[-1], side="left"))
        if start or (held and held[-1].column(key)[-1].as_py() != keys[0]):
            if start:
                held.append(batch.slice(0, start))
            yield pa.Table.from_batches(held)
            held = [batch.slice(start)]
        else:
            held.append(batch)
    if held:
        yield pa.Table.from_batches(held)


def bit_filter(hashes: DataFrame, column: str) -> bytes:
    """A bitmap of the low bits of signed hashes; its size does not depend on their number."""
    low = F.col(column).bitwiseAND(F.lit((1 << FILTER_BITS) - 1)) + 1  # these functions count from one
    rows = hashes.groupBy(F.bitmap_bucket_number(low).alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(low)).alias("bits"))
    # Written before it is collected, as shuffle files go with a table that is written, not with rows that are collected.
    made = cut(rows)
    out = np.zeros(1 << (FILTER_BITS - 3), dtype=np.uint8)
    for r in made.collect():
        at = (r["b"] - 1) * 4096
        out[at : at + 4096] = np.frombuffer(bytes(r["bits"]), dtype=np.uint8)[: len(out) - at]
    release(made)
    return out.tobytes()


def within(bits: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """Which unsigned hashes pass a filter."""
    at = (hashes & np.uint64((1 << FILTER_BITS) - 1)).astype(np.int64)
    return (bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
