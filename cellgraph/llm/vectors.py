"""Blocks of vectors: many rows packed into one, so that searches multiply matrices."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def usable(vec) -> F.Column:
    """True for a vector that is not null or empty and has only finite components."""
    bad = F.exists(vec, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce((F.size(vec) > 0) & ~bad, F.lit(False))


def pack(rows: DataFrame, keys: list[str], n: int, name: str, ordered: bool) -> DataFrame:
    """``rows(keys.., id long, vec array<double>)`` as blocks ``(keys.., <name>_ids, <name>_vecs)`` of at most ``n`` rows.

    A block is made of neighbouring rows of one partition that share the (integer) keys and the
    dimension; ``ordered`` says that rows of equal keys stand together.
    """
    schema = rows.select(*keys).schema.add(f"{name}_ids", "binary").add(f"{name}_vecs", "binary").add(f"{name}_dim", "integer")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_blocks: dict[tuple, list] = {}

        def emit(key: tuple) -> pa.RecordBatch:
            ids, vecs = zip(*open_blocks.pop(key), strict=True)
            cols = [pa.array([k], pa.int64()) for k in key[:-1]]
            cols += [pa.array([np.array(ids, dtype=np.int64).tobytes()]), pa.array([np.array(vecs, dtype=np.float64).tobytes()]), pa.array([key[-1]], pa.int32())]
            return pa.RecordBatch.from_arrays(cols, names=names)

        for b in batches:
            key_cols = [b.column(i).to_numpy(zero_copy_only=False).tolist() for i in range(len(keys))]
            ids = b.column(len(keys)).to_numpy(zero_copy_only=False).tolist()
            lists = b.column(len(keys) + 1)
            offsets = np.asarray(lists.offsets)
            flat = lists.values.to_numpy(zero_copy_only=False).astype(np.float64)
            for i, vec_id in enumerate(ids):
                vec = flat[offsets[i] : offsets[i + 1]]
                key = (*(c[i] for c in key_cols), len(vec))
                if ordered and key not in open_blocks:
                    for old in list(open_blocks):
                        yield emit(old)
                block = open_blocks.setdefault(key, [])
                block.append((vec_id, vec))
                if len(block) >= n:
                    yield emit(key)
        for old in list(open_blocks):
            yield emit(old)

    names = schema.fieldNames()
    return rows.select(*keys, "id", "vec").mapInArrow(run, schema)


def unpack(ids: bytes, vecs: bytes, dim: int) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(ids, dtype=np.int64), np.frombuffer(vecs, dtype=np.float64).reshape(-1, dim)
