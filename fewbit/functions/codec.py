"""Messages as bits: lattice indexes of given widths packed without gaps, most significant bit first."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F


def pack(index, bits) -> bytes:
    """ceil(sum(bits) / 8) bytes."""
    index, bits = np.asarray(index, np.int64), np.broadcast_to(np.asarray(bits, np.int64), np.shape(index))
    if ((index < 0) | (index >> bits > 0)).any():
        raise ValueError("an index needs more bits than it has")
    owner = np.repeat(np.arange(len(index)), bits)
    ends = np.cumsum(bits)
    place = ends[owner] - 1 - np.arange(len(owner))
    return np.packbits(((index[owner] >> place) & 1).astype(np.uint8)).tobytes()


def unpack(message: bytes, bits) -> np.ndarray:
    bits = np.asarray(bits, np.int64)
    flat = np.unpackbits(np.frombuffer(message, np.uint8))[: bits.sum()].astype(np.int64)
    ends = np.cumsum(bits)
    owner = np.repeat(np.arange(len(bits)), bits)
    place = ends[owner] - 1 - np.arange(len(owner))
    out = np.zeros(len(bits), np.int64)
    np.add.at(out, owner, flat << place)
    return out


def pack_rows(index: np.ndarray, bits: int) -> np.ndarray:
    """Messages (rows x bytes) of many index vectors of one width, packed together."""
    if ((index < 0) | (index >> bits > 0)).any():
        raise ValueError("an index needs more bits than it has")
    place = np.arange(bits - 1, -1, -1)
    return np.packbits(((index[:, :, None] >> place) & 1).astype(np.uint8).reshape(len(index), -1), axis=1)


def unpack_rows(raw: np.ndarray, bits: int, d: int) -> np.ndarray:
    flat = np.unpackbits(raw, axis=1)[:, : bits * d].reshape(len(raw), d, bits).astype(np.int64)
    return (flat << np.arange(bits - 1, -1, -1)).sum(2)


def pack_column(index: pa.Array, bits: int) -> pa.Array:
    """Packed messages of a column of index lists; rows of one length are packed together, null rows stay null."""
    ends, out = index.offsets.to_numpy(), [None] * len(index)
    size, flat, known = np.diff(ends), index.values.to_numpy(zero_copy_only=False), index.is_valid().to_numpy(zero_copy_only=False)
    for d in np.unique(size[known]):
        some = np.flatnonzero((size == d) & known)
        for i, message in zip(some, pack_rows(flat[ends[some][:, None] + np.arange(d)].astype(np.int64), bits), strict=True):
            out[i] = message.tobytes()
    return pa.array(out, pa.binary())


def pack_udf(bits: int):
    """Arrow function: array<bigint> of one width to binary."""

    @F.arrow_udf("binary")
    def packed(index: pa.Array) -> pa.Array:
        return pack_column(index, bits)

    return packed


def unpack_udf(bits: int, d: int):
    """Arrow function: binary to array<bigint> of d indexes of one width."""

    @F.arrow_udf("array<bigint>")
    def opened(message: pa.Array) -> pa.Array:
        known = message.is_valid().to_numpy(zero_copy_only=False)
        raw = np.frombuffer(b"".join(message.drop_null().to_pylist()), np.uint8).reshape(int(known.sum()), -1)
        ends = np.concatenate([[0], np.cumsum(np.where(known, d, 0))]).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(ends), pa.array(unpack_rows(raw, bits, d).ravel()), mask=pa.array(~known))

    return opened


def bit_text_sql(index: str, bits: int) -> str:
    """Spark SQL for the bits of an index as text, the codec's readable twin."""
    return f"lpad(conv({index}, 10, 2), {bits}, '0')"
