"""An index blob in the tail of a Parquet file.

The new file is the old one's bytes up to its footer, then the blob, then the old footer with
one more key/value entry that says where the blob is. Pages keep their place, so any reader
sees the same table. Only the outermost struct of the footer's compact Thrift is walked.
"""

from __future__ import annotations

import json
import zlib
from urllib.parse import unquote

import pyarrow as pa
import pyarrow.fs as pafs

KEY = "prunedknn.ivf.v1"
SIDECAR = ".ivf"
_KEY_VALUE_FIELD = 5  # fixed by the format: FileMetaData.key_value_metadata


def open_fs(uri: str) -> tuple[pafs.FileSystem, str]:
    """File system and path of a URI or a plain path."""
    if uri.startswith("file:"):
        return pafs.LocalFileSystem(), "/" + unquote(uri[5:]).lstrip("/")
    return pafs.FileSystem.from_uri(uri) if "://" in uri else (pafs.LocalFileSystem(), uri)


def _varint(buf: bytes, at: int) -> tuple[int, int]:
    out = shift = 0
    while True:
        b = buf[at]
        at += 1
        out |= (b & 0x7F) << shift
        if b < 0x80:
            return out, at
        shift += 7


def _to_varint(n: int) -> bytes:
    out = bytearray()
    while n >= 0x80:
        out.append(n & 0x7F | 0x80)
        n >>= 7
    return bytes([*out, n])


def _skip(buf: bytes, at: int, kind: int) -> int:
    if kind in (1, 2):
        return at
    if kind == 3:
        return at + 1
    if kind in (4, 5, 6):
        return _varint(buf, at)[1]
    if kind == 7:
        return at + 8
    if kind == 8:
        n, at = _varint(buf, at)
        return at + n
    if kind in (9, 10):
        head = buf[at]
        n, at = (head >> 4, at + 1) if head >> 4 != 15 else _varint(buf, at + 1)
        for _ in range(n):
            at = at + 1 if head & 15 in (1, 2) else _skip(buf, at, head & 15)
        return at
    if kind == 12:
        while buf[at]:
            step, inner = buf[at] >> 4, buf[at] & 15
            at = _skip(buf, at + 1 if step else _varint(buf, at + 1)[1], inner)
        return at + 1
    raise ValueError(f"footer: field type {kind} is not known")


def _fields(buf: bytes) -> list[tuple[int, int, int, int]]:
    """(number, type, start of the value, end) of each field of the outermost struct."""
    out, at, number = [], 0, 0
    while buf[at]:
        step, kind = buf[at] >> 4, buf[at] & 15
        at += 1
        if step:
            number += step
        else:
            raw, at = _varint(buf, at)
            number = (raw >> 1) ^ -(raw & 1)
        end = _skip(buf, at, kind)
        out.append((number, kind, at, end))
        at = end
    return out


def _entries(raw: bytes) -> list[bytes]:
    head = raw[0]
    n, at = (head >> 4, 1) if head >> 4 != 15 else _varint(raw, 1)
    out = []
    for _ in range(n):
        end = _skip(raw, at, 12)
        out.append(raw[at:end])
        at = end
    return out


def _entry(key: str, value: str) -> bytes:
    k, v = key.encode(), value.encode()
    return b"\x18" + _to_varint(len(k)) + k + b"\x18" + _to_varint(len(v)) + v + b"\x00"


def with_entry(footer: bytes, key: str, value: str) -> bytes:
    """The footer with the entry; an older one of the same key is replaced."""
    values = {n: (k, footer[a:b]) for n, k, a, b in _fields(footer)}
    own = b"\x18" + _to_varint(len(key.encode())) + key.encode()
    kept = [e for e in _entries(values[_KEY_VALUE_FIELD][1]) if not e.startswith(own)] if _KEY_VALUE_FIELD in values else []
    kept.append(_entry(key, value))
    head = bytes([len(kept) << 4 | 12]) if len(kept) < 15 else bytes([0xFC]) + _to_varint(len(kept))
    values[_KEY_VALUE_FIELD] = (9, head + b"".join(kept))
    out, last = bytearray(), 0
    for number in sorted(values):
        kind, raw = values[number]
        step = number - last
        out += bytes([step << 4 | kind]) if 0 < step < 16 else bytes([kind]) + _to_varint(number << 1)
        out += raw
        last = number
    return bytes(out) + b"\x00"


def _footer_of(raw: bytes) -> tuple[int, bytes]:
    if raw[-4:] != b"PAR1":
        raise ValueError("not a plain Parquet file (an encrypted footer is refused)")
    size = int.from_bytes(raw[-8:-4], "little")
    start = len(raw) - 8 - size
    return start, raw[start:-8]


def embed(source: str, target: str, blob: bytes) -> dict:
    """Write source with the blob to target; returns sizes and the checksum of the untouched prefix."""
    fs, path = open_fs(source)
    with fs.open_input_file(path) as f:
        raw = f.read()
    start, footer = _footer_of(raw)
    pointer = json.dumps({"offset": start, "length": len(blob), "crc": zlib.crc32(blob)})
    extended = with_entry(footer, KEY, pointer)
    out_fs, out_path = open_fs(target)
    out_fs.create_dir(out_path.rpartition("/")[0], recursive=True)
    with out_fs.open_output_stream(out_path) as f:
        for part in (raw[:start], blob, extended, len(extended).to_bytes(4, "little"), b"PAR1"):
            f.write(part)
    return {"prefix": start, "prefix_crc": zlib.crc32(raw[:start]), "bytes": start + len(blob) + len(extended) + 8}


def write_sidecar(source: str, blob: bytes) -> str:
    """For files that may not be rewritten: the blob in a file of its own beside the data file."""
    fs, path = open_fs(source)
    with fs.open_output_stream(path + SIDECAR) as f:
        f.write(zlib.crc32(blob).to_bytes(4, "little") + blob)
    return source + SIDECAR


def _read_sidecar(path: str) -> bytes | None:
    fs, own = open_fs(path)
    if fs.get_file_info(own + SIDECAR).type == pafs.FileType.NotFound:
        return None
    with fs.open_input_file(own + SIDECAR) as f:
        raw = f.read()
    return raw[4:] if zlib.crc32(raw[4:]) == int.from_bytes(raw[:4], "little") else None


def read_pointer(path: str) -> dict | None:
    import pyarrow.parquet as pq

    fs, own = open_fs(path)
    found = (pq.read_metadata(own, filesystem=fs).metadata or {}).get(KEY.encode())
    return json.loads(found) if found else None


def read_blob(path: str) -> bytes | None:
    """The blob, or None where there is none or it does not have its checksum."""
    pointer = read_pointer(path)
    if pointer is None:
        return _read_sidecar(path)
    fs, own = open_fs(path)
    with fs.open_input_file(own) as f:
        f.seek(pointer["offset"])
        blob = f.read(pointer["length"])
    return blob if zlib.crc32(blob) == pointer["crc"] else None


def read_columns(path: str, columns: list[str]) -> pa.Table:
    """Columns of one file, whole and in row order."""
    import pyarrow.parquet as pq

    fs, own = open_fs(path)
    return pq.read_table(own, columns=columns, filesystem=fs, partitioning=None)


def matrix(table: pa.Table, column: str, dim: int):
    """The vectors as float32 rows; a null vector is a row of NaN, another length an error."""
    import numpy as np

    from .schema import DimensionMismatch

    vectors = table.column(column).combine_chunks()
    if isinstance(vectors, pa.ChunkedArray):
        vectors = pa.concat_arrays(vectors.chunks) if vectors.num_chunks else pa.array([], type=pa.list_(pa.float32()))
    there = vectors.is_valid().to_numpy(zero_copy_only=False)
    flat = vectors.flatten().to_numpy(zero_copy_only=False).astype(np.float32)
    if len(flat) != int(there.sum()) * dim:
        raise DimensionMismatch(f"{column}: {len(flat)} parts in {int(there.sum())} vectors, declared {dim}")
    out = np.full((len(vectors), dim), np.nan, dtype=np.float32)
    out[there] = flat.reshape(-1, dim)
    return out
