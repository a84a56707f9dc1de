"""Vectorised word kernels shared by the text operators.

Everything here works on whole Arrow string columns: words are byte runs outside
``[\\x20\\x09-\\x0D]``, found and hashed with numpy over the UTF-8 buffer.  A span of bytes
is identified by two 64-bit lanes and its length: the bytes themselves up to 16, a
BLAKE2b digest of 128 bits beyond.  Two independent 64-bit hashes are mixed from them, so
what is told apart by both is told apart by 128 bits of the text.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U64 = np.uint64
_GOLDEN = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1
_ODD = 0x5851F42D4C957F2D


def mix64(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """Avalanche of 64-bit integers (finaliser of the splitmix family)."""
    x = x + U64(((salt + 1) * _GOLDEN) & _MASK)
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
#: Masks of the first 0..8 bytes of a little-endian lane.
_FIRST = np.array([(1 << (8 * n)) - 1 for n in range(9)], U64)


class Spans:
    """Identities of byte spans: exact up to 16 bytes, a cryptographic digest beyond."""

    __slots__ = ("low", "high", "size")

    def __init__(self, buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool = False):
        padded = np.zeros((len(buf) // 8 + 4) * 8, np.uint8)
        padded[: len(buf)] = _LOWER[buf] if lower else buf
        lanes = padded.view("<u8")
        self.size = (ends - starts).astype(np.int64)
        at, shift = starts >> 3, ((starts & 7) << 3).astype(U64)
        rest = U64(63) - shift  # one bit less, as a shift by 64 has no value

        def lane(k: int, which=slice(None)) -> np.ndarray:
            one, two = lanes[at[which] + k], lanes[at[which] + k + 1]
            return (one >> shift[which]) | ((two << rest[which]) << U64(1))

        self.low = lane(0) & _FIRST[np.minimum(self.size, 8)]
        self.high = np.zeros(len(self.size), U64)
        long = np.flatnonzero(self.size > 8)
        self.high[long] = lane(1, long) & _FIRST[np.minimum(self.size[long] - 8, 8)]
        over = np.flatnonzero(self.size > 16)
        if len(over):
            raw, digest = memoryview(padded), hashlib.blake2b
            found = b"".join([digest(raw[a:b], digest_size=16).digest() for a, b in zip(starts[over].tolist(), ends[over].tolist(), strict=True)])
            pair = np.frombuffer(found, "<u8").reshape(-1, 2)
            self.low[over], self.high[over] = pair[:, 0], pair[:, 1]

    def hash(self, salt: int = 0) -> np.ndarray:
        """64 bits; hashes of different salts are independent."""
        out = mix64(mix64(self.low, 211 + salt) ^ (self.size.astype(U64) * U64(_ODD)), 227 + salt)
        long = np.flatnonzero(self.size > 8)
        out[long] = mix64(out[long] ^ (self.high[long] * U64(_ODD)), 223 + salt)
        return out


class Words:
    """Words of a slice of documents: byte bounds, first word of each document, hashes."""

    __slots__ = ("buf", "offs", "starts", "ends", "first", "_lower", "_spans", "_hash")

    def __init__(self, buf: np.ndarray, offs: np.ndarray, lower: bool = False):
        self.buf, self.offs, self._lower, self._spans, self._hash = buf, offs, lower, None, {}
        solid = ~_SPACE[buf]
        before = np.empty_like(solid)
        after = np.empty_like(solid)
        if len(buf):
            before[0], before[1:] = False, solid[:-1]
            after[-1], after[:-1] = False, solid[1:]
            inner = offs[:-1][offs[:-1] < len(buf)]
            before[inner] = False
            inner = offs[1:][offs[1:] > 0]
            after[inner - 1] = False
        self.starts = np.flatnonzero(solid & ~before)
        self.ends = np.flatnonzero(solid & ~after) + 1
        self.first = np.searchsorted(self.starts, offs)

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    @property
    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.offs) - 1), self.counts)

    def hashed(self, salt: int = 0) -> np.ndarray:
        """A 64-bit hash of every word; two salts give 128 independent bits."""
        if salt not in self._hash:
            if self._spans is None:
                self._spans = Spans(self.buf, self.starts, self.ends, self._lower)
            self._hash[salt] = self._spans.hash(salt)
        return self._hash[salt]

    @property
    def hashes(self) -> np.ndarray:
        return self.hashed(0)

    def windows(self, k: int) -> np.ndarray:
        """Word index of every run of k words inside one document."""
        n = len(self.starts)
        if n < k:
            return np.empty(0, np.int64)
        doc = self.doc
        return np.flatnonzero(doc[: n - k + 1] == doc[k - 1 :])


def roll(h: np.ndarray, k: int, salt: int = 0) -> np.ndarray:
    """Order-sensitive hash of every k consecutive values of h."""
    weights = mix64(np.arange(k, dtype=U64), 101 + salt) | U64(1)
    out = h[: len(h) - k + 1] * weights[0]
    for j in range(1, k):
        out += h[j : len(h) - k + 1 + j] * weights[j]
    return mix64(out, k + salt)


def span_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, salt: int = 0) -> np.ndarray:
    return Spans(buf, starts, ends).hash(salt)


def text_slices(column: pa.Array, limit: int = 1 << 20):
    """Cut a string column into runs of whole documents of about `limit` bytes.

    Yields (first row, row after the last, bytes, offsets from 0); null counts as empty.
    """
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column, "").cast(pa.large_string())
    if not len(column):
        return
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.empty(0, np.uint8)
    lo = 0
    while lo < len(column):
        hi = max(lo + 1, int(np.searchsorted(offs, offs[lo] + limit, "right")) - 1)
        yield lo, hi, raw[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo]
        lo = hi


def ragged(lengths: np.ndarray) -> np.ndarray:
    """0..len-1 within each run."""
    total = int(lengths.sum())
    ends = np.cumsum(lengths)
    return np.arange(total) - np.repeat(ends - lengths, lengths)


def list_array(lengths: np.ndarray, values: np.ndarray, kind: pa.DataType) -> pa.Array:
    offs = np.zeros(len(lengths) + 1, np.int32)
    np.cumsum(lengths, out=offs[1:])
    return pa.ListArray.from_arrays(pa.array(offs, pa.int32()), pa.array(values, kind))


def as_long(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x).view(np.int64)
