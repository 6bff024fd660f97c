"""Word splitting of Arrow text columns with numpy, a few megabytes at a time."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

#: Texts are cut into chunks of whole documents near this many bytes, so working arrays stay small.
CHUNK_BYTES = 2 << 20


def byte_table(separators: bytes) -> np.ndarray:
    """True for bytes that belong to words."""
    out = np.ones(256, bool)
    out[list(separators)] = False
    return out


#: Words of the near-duplicate and substring operators: all but space and the five ASCII controls.
NOT_BLANK = byte_table(bytes([0x20, *range(0x09, 0x0E)]))
#: Words of decontamination, after lower-casing: ASCII digits and letters, and everything beyond ASCII.
ALPHANUMERIC = byte_table(bytes([*range(0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)]))

LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 0x20


@dataclass
class Words:
    """Words of some documents: ``data[start[i]:end[i]]``; document d has words first[d] .. first[d + 1]."""

    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray

    def word(self, i: int) -> bytes:
        return self.data[self.start[i] : self.end[i]].tobytes()


def chunks(texts: pa.Array, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(number of the first document, bytes, document offsets) of pieces; a null text is empty."""
    texts = texts.cast(pa.large_string())
    if texts.null_count:
        texts = texts.fill_null("")
    n = len(texts)
    if not n:
        return
    offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + n + 1]
    raw = texts.buffers()[2]
    data = np.frombuffer(raw, np.uint8) if raw is not None else np.zeros(0, np.uint8)
    at = 0
    while at < n:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1)
        yield at, data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]
        at = to


def split_words(data: np.ndarray, offsets: np.ndarray, table: np.ndarray, lower: bool) -> Words:
    """Words never span two documents."""
    if lower:
        data = LOWER[data]
    inside = table[data]
    before = np.zeros(len(data) + 1, bool)
    before[1:] = inside
    before[offsets] = False
    start = np.flatnonzero(inside & ~before[:-1])
    after = np.zeros(len(data) + 1, bool)
    after[:-1] = inside
    after[offsets] = False
    end = np.flatnonzero(inside & ~after[1:]) + 1
    return Words(data, start, end, np.searchsorted(start, offsets))


_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15 | 1)
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def power_table(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the multiplier and of its inverse modulo 2**64."""
    size = max(CHUNK_BYTES + 1, n)
    if size not in _powers:
        inverse = np.uint64(pow(int(_MULTIPLIER), -1, 1 << 64))
        tables = []
        for base in (_MULTIPLIER, inverse):
            steps = np.full(size, base)
            steps[0] = 1
            tables.append(np.cumprod(steps))
        if size > CHUNK_BYTES + 1:
            return tables[0], tables[1]
        _powers[size] = (tables[0], tables[1])
    return _powers[size]


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit values."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_TAIL = np.array([0, *((1 << 8 * k) - 1 for k in range(1, 9))], np.uint64)
#: Longer words are hashed one by one.
_LONG = 128


def word_hashes(words: Words, salt: int = 0) -> np.ndarray:
    """64-bit hash of every word, the same in every chunk: its 8-byte blocks are scrambled one after the other."""
    size = words.end - words.start
    h = mix(size.astype(np.uint64) + np.uint64((salt * 0x9E3779B97F4A7C15 + 1) % (1 << 64)))
    padded = np.concatenate([words.data, np.zeros(8, np.uint8)])
    blocks = np.ndarray(len(words.data) + 1, "<u8", padded, 0, (1,))
    left, at = np.flatnonzero(size <= _LONG), 0
    while len(left):
        rest = size[left] - at
        block = blocks[words.start[left] + at] & _TAIL[np.minimum(rest, 8)]
        h[left] = mix(h[left] * _MULTIPLIER ^ block)
        left, at = left[rest > 8], at + 8
    for i in np.flatnonzero(size > _LONG):
        digest = hashlib.blake2b(words.word(i), digest_size=8, salt=salt.to_bytes(8, "little")).digest()
        h[i] = np.uint64(int.from_bytes(digest, "little"))
    return h


def spread(lo: np.ndarray, size: np.ndarray) -> np.ndarray:
    """lo[0], lo[0] + 1, .. (size[0] of them), lo[1], .."""
    size = size.astype(np.int64)
    return np.repeat(lo - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))


def same_bytes(a: Words, i: np.ndarray, b: Words, j: np.ndarray) -> np.ndarray:
    """Whether word i[k] of ``a`` has the bytes of word j[k] of ``b``."""
    size = a.end[i] - a.start[i]
    same = size == b.end[j] - b.start[j]
    at = np.flatnonzero(same)
    equal = a.data[spread(a.start[i[at]], size[at])] == b.data[spread(b.start[j[at]], size[at])]
    wrong = np.repeat(at, size[at])[~equal]
    same[wrong] = False
    return same
