"""Vector columns as matrices and back: lists of doubles, or packed numbers of 4 or 2 bytes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from .solvers import bf16_pack, bf16_round, bf16_unpack

#: Bytes of a stored number, by precision; 16-bit numbers are bfloat16.
STORED_BYTES = {"float64": 8, "float32": 4, "mixed": 2, "bf16_all": 2}


def to_matrix(column: pa.Array | pa.ChunkedArray, rank: int) -> np.ndarray:
    """(n, rank) float64 from vectors of rank numbers: lists, or packed bytes whose number tells their kind."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_binary(column.type):
        n = len(column)
        ends = np.frombuffer(column.buffers()[1], dtype=np.int32)[column.offset : column.offset + n + 1] if n else np.zeros(1, dtype=np.int32)
        size = int(ends[-1] - ends[0])
        width = size // max(1, n * rank)
        if width not in (0, 2, 4) or size != n * rank * width:
            raise ValueError(f"vectors of another length than {rank}")
        raw = np.frombuffer(column.buffers()[2], dtype=np.uint8)[ends[0] : ends[-1]] if size else np.zeros(0, dtype=np.uint8)
        return (bf16_unpack(raw.view("<u2")) if width == 2 else raw.view("<f4")).reshape(-1, rank).astype(np.float64)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    if len(flat) != len(column) * rank:
        raise ValueError(f"vectors of another length than {rank}")
    return flat.reshape(-1, rank).astype(np.float64, copy=False)


def to_lists(rows: np.ndarray, kind: pa.DataType | None = None) -> pa.ListArray:
    n, width = rows.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * width + 1, max(width, 1), dtype=np.int32)[: n + 1]), pa.array(np.ascontiguousarray(rows).reshape(-1), type=kind or pa.float64()))


def to_stored(rows: np.ndarray, precision: str) -> pa.Array:
    """Vectors as they are stored and moved: lists of doubles, or packed float32 or bfloat16."""
    if precision == "float64":
        return to_lists(np.asarray(rows, dtype=np.float64))
    packed = np.ascontiguousarray(rows, dtype="<f4") if precision == "float32" else bf16_pack(rows)
    n, width = len(packed), packed.shape[1] * packed.itemsize
    return pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(np.arange(0, n * width + 1, max(width, 1), dtype=np.int32)[: n + 1].tobytes()), pa.py_buffer(packed.tobytes())])


def stored_type(precision: str) -> str:
    return "id long, vec array<double>" if precision == "float64" else "id long, vec binary"


def rounded_to(rows: np.ndarray, precision: str) -> np.ndarray:
    """Values at the precision of their storage."""
    return rows if precision == "float64" else rows.astype(np.float32) if precision == "float32" else bf16_round(rows)


def ids(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    return column.to_numpy(zero_copy_only=False) if isinstance(column, pa.Array) else column.to_numpy()
