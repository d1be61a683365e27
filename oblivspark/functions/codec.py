"""Rows as records of one fixed width: an order-preserving key and a padded payload.

The width of a record depends on the schema and on public widths alone, so a block of records tells nothing by its length.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql.types import StructType

#: Bytes that a string or binary column gets unless its public width is given.
DEFAULT_WIDTH = 32


class WidthExceeded(ValueError):
    """A value is longer than the public width of its column."""


def ordered_u64(values: np.ndarray) -> np.ndarray:
    """Unsigned 64-bit integers in the order of the values (numbers; -0.0 equals 0.0, NaN comes last)."""
    if values.dtype.kind == "f":
        v = values.astype(np.float64) + 0.0
        v[v == 0] = 0.0
        v = np.where(np.isnan(v), np.nan, v)
        bits = v.view(np.uint64)
        top = np.uint64(1 << 63)
        return np.where(bits & top, ~bits, bits | top)
    return values.astype(np.int64).view(np.uint64) ^ np.uint64(1 << 63)


def as_bytes(words: np.ndarray) -> np.ndarray:
    """Big-endian bytes, a row of 8 for each word."""
    return words.astype(">u8").view(np.uint8).reshape(len(words), 8)


@dataclass
class Codec:
    """Schema and public string widths to records and back. Columns: a flag byte, then 8 bytes, or a 4-byte length and the padded bytes, or a fixed list of floats."""

    schema: StructType
    widths: dict[str, int] = field(default_factory=dict)

    def __post_init__(self):
        self.arrow = {f.name: _arrow_type(f.dataType.simpleString()) for f in self.schema}
        self.sizes = {}
        for f in self.schema:
            t = f.dataType.simpleString()
            if t in ("string", "binary"):
                self.sizes[f.name] = 4 + self.widths.get(f.name, DEFAULT_WIDTH)
            elif t == "array<float>":
                self.sizes[f.name] = 4 * self.widths.get(f.name, 64)
            else:
                self.sizes[f.name] = 8
        self.width = sum(self.sizes.values()) + len(self.sizes)

    def encode(self, batch: pa.RecordBatch) -> np.ndarray:
        out = np.zeros((batch.num_rows, self.width), np.uint8)
        at = 0
        for name, size in self.sizes.items():
            col = batch.column(batch.schema.get_field_index(name))
            valid = col.is_valid().to_numpy(zero_copy_only=False)
            out[:, at] = valid
            at += 1
            if pa.types.is_string(self.arrow[name]) or pa.types.is_binary(self.arrow[name]):
                lengths = _padded(col, out[:, at + 4 : at + size], name)
                out[:, at : at + 4] = lengths.astype(">u4").view(np.uint8).reshape(-1, 4)
            elif pa.types.is_list(self.arrow[name]):
                flat = np.zeros((batch.num_rows, size // 4), np.float32)
                for i, v in enumerate(col.to_pylist()):
                    if v is not None:
                        if len(v) != size // 4:
                            raise WidthExceeded(f"{name}: {len(v)} items, its width is {size // 4}")
                        flat[i] = v
                out[:, at : at + size] = flat.view(np.uint8).reshape(batch.num_rows, size)
            else:
                out[:, at : at + 8] = _numbers(col).view(np.uint8).reshape(-1, 8)
            at += size
        return out

    def decode(self, rec: np.ndarray) -> list[pa.Array]:
        out, at = [], 0
        for name, size in self.sizes.items():
            kind = self.arrow[name]
            valid, at = rec[:, at] == 1, at + 1
            part = np.ascontiguousarray(rec[:, at : at + size])
            at += size
            if pa.types.is_string(kind) or pa.types.is_binary(kind):
                n = np.where(valid, part[:, :4].copy().view(">u4").reshape(-1), 0).astype(np.int32)
                offsets = np.concatenate(([0], np.cumsum(n))).astype(np.int32)
                data = part[:, 4:][np.arange(size - 4) < n[:, None]]
                buffers = [pa.py_buffer(np.packbits(valid, bitorder="little").tobytes()), pa.py_buffer(offsets.tobytes()), pa.py_buffer(data.tobytes())]
                out.append(pa.Array.from_buffers(pa.binary(), len(part), buffers).cast(kind))
            elif pa.types.is_list(kind):
                rows = part.view(np.float32).reshape(len(part), -1)
                out.append(pa.array([r.tolist() if ok else None for r, ok in zip(rows, valid)], kind))
            else:
                out.append(_column(part.view(np.int64).reshape(-1), kind, ~valid))
        return out


def _padded(col: pa.Array, to: np.ndarray, name: str) -> np.ndarray:
    """Write each value into its row of ``to``, which is zero so far; lengths, 0 for nulls."""
    col = col.cast(pa.large_binary()).fill_null(b"")
    lengths = pc.binary_length(col).to_numpy(zero_copy_only=False).astype(np.int64)
    if lengths.max(initial=0) > to.shape[1]:
        raise WidthExceeded(f"{name}: {lengths.max()} bytes, its width is {to.shape[1]}")
    if len(col) and lengths.sum():
        offsets = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + len(col) + 1]
        data = np.frombuffer(col.buffers()[2], np.uint8)[offsets[0] : offsets[-1]]
        to[np.arange(to.shape[1]) < lengths[:, None]] = data
    return lengths


def _numbers(col: pa.Array) -> np.ndarray:
    """Any 8-byte-wide type as raw 64-bit values; nulls as 0."""
    t = col.type
    if pa.types.is_floating(t):
        return col.cast(pa.float64()).fill_null(0.0).to_numpy(zero_copy_only=False).astype(np.float64).view(np.int64)
    if pa.types.is_boolean(t):
        return col.cast(pa.int8()).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    if pa.types.is_timestamp(t):
        col = col.cast(pa.timestamp("us")).cast(pa.int64())
    elif pa.types.is_date(t):
        col = col.cast(pa.int32())
    elif pa.types.is_decimal(t):
        return np.array([0 if v is None else int(v.scaleb(t.scale)) for v in col.to_pylist()], np.int64)
    return col.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)


def _column(raw: np.ndarray, kind: pa.DataType, mask: np.ndarray) -> pa.Array:
    if pa.types.is_floating(kind):
        return pa.array(raw.view(np.float64), mask=mask).cast(kind)
    if pa.types.is_boolean(kind):
        return pa.array(raw != 0, mask=mask)
    if pa.types.is_timestamp(kind):
        return pa.array(raw, pa.int64(), mask=mask).cast(pa.timestamp("us")).cast(kind)
    if pa.types.is_date(kind):
        return pa.array(raw.astype(np.int32), pa.int32(), mask=mask).cast(kind)
    if pa.types.is_decimal(kind):
        import decimal

        return pa.array([None if m else decimal.Decimal(int(v)).scaleb(-kind.scale) for v, m in zip(raw, mask)], kind)
    return pa.array(raw, pa.int64(), mask=mask).cast(kind)


def _arrow_type(name: str) -> pa.DataType:
    plain = {
        "string": pa.string(), "binary": pa.binary(), "bigint": pa.int64(), "int": pa.int32(), "smallint": pa.int16(), "tinyint": pa.int8(),
        "double": pa.float64(), "float": pa.float32(), "boolean": pa.bool_(), "date": pa.date32(), "timestamp_ntz": pa.timestamp("us"),
        "timestamp": pa.timestamp("us", "UTC"), "array<float>": pa.list_(pa.float32()),
    }
    if name in plain:
        return plain[name]
    if name.startswith("decimal("):
        p, s = map(int, name[8:-1].split(","))
        if p <= 18:
            return pa.decimal128(p, s)
    raise TypeError(f"no fixed-width form for {name}")


@dataclass(frozen=True)
class Key:
    """A sort key: column, direction, and whether nulls come first."""

    name: str
    ascending: bool = True
    nulls_first: bool = True


def as_keys(keys) -> list[Key]:
    return [k if isinstance(k, Key) else Key(k) for k in ([keys] if isinstance(keys, (str, Key)) else keys)]


def encode_keys(batch: pa.RecordBatch, keys: list[Key], widths: dict[str, int]) -> np.ndarray:
    """Bytes that compare as the keys do, column after column."""
    parts = []
    for k in keys:
        col = batch.column(batch.schema.get_field_index(k.name))
        valid = col.is_valid().to_numpy(zero_copy_only=False)
        if pa.types.is_string(col.type) or pa.types.is_large_string(col.type) or pa.types.is_binary(col.type):
            w = widths.get(k.name, DEFAULT_WIDTH)
            body = np.zeros((batch.num_rows, w + 2), np.uint8)
            lengths = _padded(col, body[:, :w], k.name)
            body[:, w:] = lengths.astype(">u2").view(np.uint8).reshape(-1, 2)  # parts strings that end in zero bytes
        else:
            raw = _numbers(col)
            body = as_bytes(ordered_u64(raw.view(np.float64) if pa.types.is_floating(col.type) else raw))
        if not k.ascending:
            body = ~body
        body[~valid] = 0
        flag = np.where(valid, 1, 0 if k.nulls_first else 2).astype(np.uint8)
        parts += [flag[:, None], body]
    return np.hstack(parts) if parts else np.zeros((batch.num_rows, 0), np.uint8)


def key_words(key: np.ndarray) -> np.ndarray:
    """Key bytes as rows of 64-bit words of the same order."""
    pad = -key.shape[1] % 8
    if pad:
        key = np.hstack((key, np.zeros((len(key), pad), np.uint8)))
    return np.ascontiguousarray(key).view(">u8").astype(np.uint64)
