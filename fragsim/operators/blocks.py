"""Overlaps of bags block by block: no row per (pair, action) is ever shuffled.

Fragments of near sizes are packed into *blocks* of some thousand, each with the hashes of its elements and an index
from element to fragment.  The rows of the block table, not those of the fragments, meet each other, and one task
counts all overlaps between two blocks in memory: elements that many fragments of both blocks have by a matrix
product, the others by looking up one block's index.  What leaves the task is the pairs that pass, or counts of them.

An element is a 64-bit hash of an action and its occurrence (``bag``), its frequency (``pair``) or nothing more
(``set``), so every kind of overlap is the size of an intersection.  ``action+pair`` has elements of the last two kinds: pairs
meet by an action and overlap by frequencies, so that their overlap may be zero.  A bag whose pairs need o common elements may keep
``slack`` < o of its elements, the most frequent ones of its block, out of the lookup: a pair above the threshold has
o - slack common ones among the rest.  Those that have are then counted whole.  Blocks that are searched by prefixes
are larger, since a search pays for the elements of a block and for the lookups, hardly for the pairs of fragments.

Blocks can hold further columns of their fragments, which leave the task with the pairs: no pair is joined to them.

The data of a block are a file of the shared folder, and what meets is names of files: a task opens the blocks of its
pairs and holds the last ones, so neither the engine's memory nor a shuffle has the data of a pair.  Where Arrow cannot
open the shared folder, the data go along with the rows.
"""

from __future__ import annotations

import pickle
import re
import uuid
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyarrow.fs import FileSystem
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fragsim.config import DetectConfig
from fragsim.sources.tables import shared_folder, staged

#: Fragments and elements of a block at most (a single larger fragment is a block of its own).
ROWS, ELEMENTS = 2_000, 600_000
#: The same for blocks that are searched by prefixes, and the least number of such blocks (for the cores) of ROWS fragments or fewer.
PREFIX_ROWS, PREFIX_ELEMENTS, PREFIX_BLOCKS = 4_000, 1_500_000, 32
#: Pairs of blocks in a task, blocks in a row that meet the same other one there, and blocks that a process holds.
MEET, TURN, HELD = 32, 4, 6
#: Rows of the block table in a partition when its rows meet.
NAMES = 1_000
#: Cells of the matrix of counts that is held at once in a search by prefixes.
CELLS = 1 << 22
#: Lookups that are counted at once, and the number per pair of fragments from which a matrix product is cheaper.
STEP, DENSE = 1 << 20, 0.006
#: Share in percent of the common elements that a pair needs which may lie in the suffix: the more, the fewer lookups and
#: the weaker the bound on a pair before it is counted whole.
SUFFIX_PCT = 90
PAIRS = "left_id long, right_id long, overlap long, left_total long, right_total long"
_P, _Q = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)


@dataclass
class Block:
    """Columns of the fragments and their elements: by fragment (``cols``, rare ones first), by element (``rows``)."""

    ids: np.ndarray
    size: np.ndarray
    total: np.ndarray
    home: np.ndarray
    mask: np.ndarray
    tag: np.ndarray
    asked: np.ndarray
    words: np.ndarray
    rowptr: np.ndarray
    cols: np.ndarray
    colptr: np.ndarray
    rows: np.ndarray
    first: np.ndarray
    kept: pa.Table


def _hashed(h: np.ndarray, k: np.ndarray) -> np.ndarray:
    x = h ^ (k.astype(np.uint64) * _P)
    x = (x ^ (x >> np.uint64(29))) * _Q
    return x ^ (x >> np.uint64(32))


def elements(h: np.ndarray, f: np.ndarray, kind: str) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the elements of (action hash, frequency), and the place each comes from."""
    place = np.arange(len(h))
    if kind == "bag":
        place = np.repeat(place, f)
        nth = np.arange(len(place)) - np.repeat(np.cumsum(f) - f, f)
        return _hashed(h[place], nth), place
    if kind == "action+pair":
        return np.stack([h, _hashed(h, f)], axis=1).reshape(-1), np.repeat(place, 2)
    return (_hashed(h, f) if kind == "pair" else h), place


def pack(columns: list[np.ndarray], count: np.ndarray, h: np.ndarray, f: np.ndarray, kind: str, kept: pa.Table) -> bytes:
    """A block of fragments with ``count`` actions each; ``first`` marks the elements that stand for an action's first occurrence."""
    value, place = elements(h, f, kind)
    row = np.repeat(np.arange(len(count)), count)[place]
    words, col = np.unique(value, return_inverse=True)
    df = np.bincount(col, minlength=len(words))
    order = np.lexsort((col, df[col], row))
    cols = col[order].astype(np.uint32)
    rowptr = np.searchsorted(row[order], np.arange(len(count) + 1))
    rows = row[np.argsort(col, kind="stable")].astype(np.uint32)
    first = np.zeros(len(words), bool)
    first[col[np.diff(place, prepend=-1) > 0]] = True
    block = Block(*columns, words, rowptr, cols, np.concatenate([[0], np.cumsum(df)]), rows, first, kept)
    return pa.compress(pickle.dumps(block, 5), "zstd", asbytes=True)


def _store(place: str) -> tuple[FileSystem, str]:
    return FileSystem.from_uri(re.sub("^s3[an]:", "s3:", place))


def data_folder(root: str) -> str | None:
    """A new folder for the data of blocks, or none where Arrow cannot open the store."""
    folder = f"{root}/fragsim-data-{uuid.uuid4().hex}"
    try:
        store, path = _store(folder)
        store.create_dir(path, recursive=True)
    except (OSError, pa.ArrowException):
        return None
    return folder


def _packed(batches: Iterator[pa.RecordBatch], kind: str, most_rows: int, most: int, folder: str | None) -> Iterator[pa.RecordBatch]:
    held: list[tuple] = []
    rows = weight = 0

    def block() -> pa.RecordBatch:
        columns = [np.concatenate(c) for c in zip(*(x[0] for x in held), strict=True)]
        count, h, f = (np.concatenate([x[i] for x in held]) for i in (1, 2, 3))
        size, home, mask, asked = columns[1], columns[3], columns[4], columns[6]
        homes = int(np.bitwise_or.reduce(np.where(home >= 0, np.int64(1) << np.maximum(home, 0), 0)))
        kept = pa.concat_tables(x[4] for x in held).combine_chunks()
        data = pack(columns, count, h, f, kind, kept)
        if folder:
            # A name of its own: a task that runs twice leaves a file that nothing names.
            place = f"{folder}/{uuid.uuid4().hex}"
            store, path = _store(place)
            with store.open_output_stream(path) as out:
                out.write(data)
            data = place
        row = [[int(size.min())], [int(size.max())], [homes], [int(np.bitwise_or.reduce(mask))], [bool(asked.any())], [data]]
        return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(row, (*[pa.int64()] * 4, pa.bool_(), pa.string() if folder else pa.binary()), strict=True)], ["lo", "hi", "homes", "masks", "asked", "data"])

    for batch in batches:
        columns = [c.to_numpy(zero_copy_only=False) for c in batch.columns[:7]]
        lists, freqs = batch.column(7), batch.column(8)
        bounds = lists.offsets.to_numpy()
        h, f = (x.flatten().to_numpy(zero_copy_only=False) for x in (lists, freqs))
        h, bounds = h.view(np.uint64), bounds - bounds[0]
        kept = pa.table(batch.columns[9:], [f"x_{x.name}" for x in list(batch.schema)[9:]])
        at = 0
        turns = np.append(np.flatnonzero(np.diff(columns[6])) + 1, len(columns[6]))
        heavy = np.concatenate([[0], np.cumsum(columns[2] if kind == "bag" else np.diff(bounds) * (2 if kind == "action+pair" else 1))])
        while at < len(columns[0]):
            if held and held[-1][0][6][-1] != columns[6][at]:
                yield block()
                held, rows, weight = [], 0, 0
            room = int(np.searchsorted(heavy, heavy[at] + most - weight, "right")) - 1
            to = min(at + most_rows - rows, room, int(turns[np.searchsorted(turns, at, "right")]))
            if to <= at and held:
                yield block()
                held, rows, weight = [], 0, 0
                continue
            to = max(to, at + 1)
            part = slice(bounds[at], bounds[to])
            held.append(([c[at:to] for c in columns], np.diff(bounds[at : to + 1]), h[part], f[part], kept.slice(at, to - at)))
            rows, weight, at = rows + to - at, weight + int(heavy[to] - heavy[at]), to
            if rows >= most_rows or weight >= most:
                yield block()
                held, rows, weight = [], 0, 0
    if held:
        yield block()


def packing(banded: DataFrame, root: str, element: str = "bag", queries: DataFrame | None = None, tag: str | None = None, prefix: bool = False, keep: Sequence[str] = ()) -> DataFrame:
    """The plan of the block table, whose data go to a folder below ``root``; ``banded`` has home_band and cand_bands, ``tag``
    names a column of longs (none: never equal), ``keep`` columns that the blocks hold."""
    rows = banded.where("fragment_id is not null")
    if queries is None:
        rows = rows.withColumn("_asked", F.lit(1))
    else:
        asked = queries.select("fragment_id").distinct().withColumn("_asked", F.lit(1))
        rows = rows.join(asked, "fragment_id", "left")
    mask = F.aggregate("cand_bands", F.lit(0).cast("long"), lambda m, b: m.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), b.cast("int"))))
    long = lambda c, none=-1: F.coalesce(c.cast("long"), F.lit(none).cast("long"))
    rows = rows.select(
        F.col("fragment_id").cast("long").alias("fragment_id"), long(F.col("n_tokens")).alias("n_tokens"), long(F.col("action_total"), 0).alias("total"), long(F.col("home_band")).alias("home"),
        long(mask, 0).alias("mask"), long(F.col(tag) if tag else F.lit(None)).alias("tag"), long(F.col("_asked"), 0).alias("asked"),
        F.transform(F.map_keys("actions"), lambda a: F.xxhash64(a)).alias("h"), F.transform(F.map_values("actions"), lambda n: n.cast("int")).alias("f"), *keep,
    )
    n = banded.count()
    size, most = (max(min(PREFIX_ROWS, -(-n // PREFIX_BLOCKS)), min(PREFIX_ROWS, ROWS // 4)), PREFIX_ELEMENTS) if prefix else (ROWS, ELEMENTS)
    parts = max(1, -(-n // size))  # ranges are near equal: a quarter more in a block leaves no remnants
    # The query set has blocks of its own, so the others do not meet each other.
    dealt = rows.repartitionByRange(parts, "asked", "n_tokens", "fragment_id").sortWithinPartitions("asked")
    folder = data_folder(root)
    made = partial(_packed, kind=element, most_rows=size * 5 // 4 if prefix else size, most=most, folder=folder)
    dealt = dealt.mapInArrow(made, f"lo long, hi long, homes long, masks long, asked boolean, data {'string' if folder else 'binary'}")
    return dealt.select(F.monotonically_increasing_id().alias("block"), "*")


#: Data in the rows of a block table are compressed; a codec of the file would only hold buffers of their size outside the heap.
CODEC = {"compression": "none"}


def packed(banded: DataFrame, *args, **kinds) -> DataFrame:
    """The block table of one run: ``packing`` written to the shared folder."""
    return staged(packing(banded, shared_folder(banded.sparkSession), *args, **kinds), "blocks", **CODEC)


def block_pairs(blocks: DataFrame, gamma_pct: int | None, old: DataFrame | None = None) -> DataFrame:
    """a, x, b, y: numbers and data (or files of data) of the blocks of which some fragments may meet, each pair once.  The
    blocks of ``old`` meet those of ``blocks`` and not each other."""
    names = ["block", "lo", "hi", "homes", "masks", "asked", "data"]
    named = blocks.schema["data"].dataType.simpleString() == "string"

    def met_by(others: DataFrame, once: bool) -> DataFrame:
        if named:
            others = others.coalesce(-(-others.count() // NAMES) or 1)
        a, b = (d.select(*(F.col(n).alias(f"{s}_{n}") for n in names)) for s, d in (("a", blocks), ("b", others)))
        on = F.col("a_asked") | F.col("b_asked")
        on &= (F.col("a_homes").bitwiseAND(F.col("b_masks")) != 0) | (F.col("b_homes").bitwiseAND(F.col("a_masks")) != 0)
        if once:
            on &= F.col("a_block") <= F.col("b_block")
        if gamma_pct is not None:
            on &= (F.col("a_hi") * 100 >= F.col("b_lo") * gamma_pct) & (F.col("b_hi") * 100 >= F.col("a_lo") * gamma_pct)
        met = a.join(b.hint("shuffle_replicate_nl"), on)
        return met.select(F.col("a_block").alias("a"), F.col("a_data").alias("x"), F.col("b_block").alias("b"), F.col("b_data").alias("y"))

    if named:
        blocks = blocks.coalesce(-(-blocks.count() // NAMES) or 1)
    met = met_by(blocks, True)
    if old is not None:
        # Numbers below zero, which no block of this table has.
        met = met.unionByName(met_by(old.withColumn("block", -1 - F.shiftrightunsigned(F.xxhash64("data"), 1)), False))
    if not named:
        return met
    # Neighbours meet a block one after the other, so it is opened once for all of them.  The low 33 bits count in a partition.
    turn = [F.shiftright("a", 33), F.floor(F.pmod("a", F.lit(1 << 33)) / TURN), "b", "a"]
    tasks = max(blocks.sparkSession.sparkContext.defaultParallelism, -(-met.count() // MEET))
    return met.repartitionByRange(tasks, *turn).sortWithinPartitions(*turn)


def _map(a: Block, b: Block) -> np.ndarray:
    """For each element of ``a`` its place in ``b`` or -1."""
    at = np.minimum(np.searchsorted(b.words, a.words), max(len(b.words) - 1, 0))
    return np.where(b.words[at] == a.words, at, -1) if len(b.words) else np.full(len(a.words), -1)


def common(a: Block, b: Block, first: bool | None = None) -> np.ndarray:
    """Matrix of the numbers of common elements; with ``first`` of those alone that are so marked, or not."""
    out = np.zeros((len(a.ids), len(b.ids)), np.int32)
    row = np.repeat(np.arange(len(a.ids)), np.diff(a.rowptr))
    place = _map(a, b)
    if first is not None:
        place = np.where(a.first == first, place, -1)
    place = place[a.cols]
    row, place = row[place >= 0], place[place >= 0]
    _count(out, row, place, b)
    return out


def _count(out: np.ndarray, row: np.ndarray, place: np.ndarray, b: Block) -> None:
    """Adds to (row, fragment of ``b``) one for each element at ``place`` that the fragment has."""
    df_b = np.diff(b.colptr)
    work = np.bincount(place, minlength=len(b.words)) * df_b
    dense = np.flatnonzero(work > DENSE * out.size)
    if len(dense):
        for at in range(0, len(dense), 512):
            part = dense[at : at + 512]
            number = np.full(len(b.words), -1)
            number[part] = np.arange(len(part))
            left, right = np.zeros((len(out), len(part)), np.float32), np.zeros((len(part), out.shape[1]), np.float32)
            take = number[place] >= 0
            left[row[take], number[place[take]]] = 1
            for k, c in enumerate(part.tolist()):
                right[k, b.rows[b.colptr[c] : b.colptr[c + 1]]] = 1
            out += (left @ right).astype(out.dtype)
        rare = np.ones(len(b.words), bool)
        rare[dense] = False
        row, place = row[rare[place]], place[rare[place]]
    many = df_b[place]
    ends = np.cumsum(many)
    flat, at, width, one = out.reshape(-1), 0, out.shape[1], out.dtype.type(1)
    while at < len(place):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + STEP, "right")))
        n = many[at:to]
        start = b.colptr[place[at:to]] - (np.cumsum(n) - n)
        where = np.repeat(start, n) + np.arange(int(n.sum()))
        np.add.at(flat, np.repeat(row[at:to].astype(np.int64) * width, n) + b.rows[where], one)
        at = to


def needed(total: np.ndarray, cfg: DetectConfig) -> np.ndarray:
    """Fewest common elements that a pair with this denominator needs."""
    return total * cfg.theta_pct // 100 + (0 if cfg.inclusive and cfg.theta_pct else 1)


def _prefix(a: Block, cfg: DetectConfig) -> tuple[np.ndarray, ...]:
    """Needed elements, length of the suffix and number of elements of each fragment; fragment and column of each element
    of a prefix.  They are the same whatever the other block, so the block keeps them."""
    kept = a.__dict__.get("_prefix")
    if kept is None or kept[0] != cfg:
        need, length = needed(a.total, cfg), np.diff(a.rowptr)
        slack = need * SUFFIX_PCT // 100
        many = np.maximum(length - slack, 0)
        row = np.repeat(np.arange(len(a.ids), dtype=np.int32), many)
        cols = a.cols[np.arange(len(row)) + np.repeat(a.rowptr[:-1] - (np.cumsum(many) - many), many)]
        a.__dict__["_prefix"] = kept = (cfg, need, slack, length, row, cols)
    return kept[1:]


def _passing(a: Block, b: Block, cfg: DetectConfig, rising: bool | None) -> tuple[np.ndarray, ...]:
    """Places, overlaps and numbers of common actions of the pairs that may be above the threshold, found by the prefixes of
    ``a``.  ``rising`` restricts them to smaller bags in ``a``, equal ones included where it is true."""
    need, slack, length, row, cols = _prefix(a, cfg)
    place = _map(a, b)
    at_b = place[cols]
    use = np.flatnonzero(at_b >= 0)
    row, at_b = row[use], at_b[use]
    step = max(1, CELLS // max(1, len(b.ids)))
    kind = np.uint16 if length.max(initial=0) < 60_000 else np.int32
    found = [(np.zeros(0, np.int64),) * 2]
    for at in range(0, len(a.ids), step):
        s, e = np.searchsorted(row, [at, at + step])
        if s == e:
            continue
        out = np.zeros((min(step, len(a.ids) - at), len(b.ids)), kind)
        _count(out, row[s:e] - at, at_b[s:e], b)
        lo = (need - slack)[at : at + step]
        i, j = np.divmod(np.flatnonzero(out >= np.clip(lo, 1, np.iinfo(kind).max).astype(kind)[:, None]), len(b.ids))
        bound = out[i, j] + slack[at + i]
        i += at
        keep = 100 * bound >= cfg.theta_pct * share_of(a.total[i], b.total[j], bound, cfg.denom)
        if rising is not None:
            keep &= a.total[i] <= b.total[j] if rising else a.total[i] < b.total[j]
        i, j = i[keep], j[keep]
        keep = _near(a, b, i, j, cfg)
        found.append((i[keep], j[keep]))
    i, j = (np.concatenate(x) for x in zip(*found, strict=True))
    return i, j, *_whole(a, b, place, i, j)


def _whole(a: Block, b: Block, place: np.ndarray, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Overlaps and numbers of common actions of the pairs, which come sorted by ``i``; ``place`` is ``_map(a, b)``."""
    overlap, actions = np.zeros(len(i), np.int64), np.zeros(len(i), np.int64)
    mark = np.zeros(len(b.words), np.int8)
    length = np.diff(b.rowptr)
    turns = np.append(np.flatnonzero(np.diff(i, prepend=-1)), len(i)).tolist()
    for s, e in zip(turns, turns[1:], strict=False):
        own = place[a.cols[a.rowptr[i[s]] : a.rowptr[i[s] + 1]]]
        own = own[own >= 0]
        mark[own] = 1 + 2 * b.first[own]
        for at in range(s, e, 1024):
            q = j[at : min(at + 1024, e)]
            n = length[q]
            starts = np.cumsum(n) - n
            hit = mark[b.cols[np.repeat(b.rowptr[q] - starts, n) + np.arange(int(n.sum()))]]
            overlap[at : at + len(q)] = np.add.reduceat(hit & 1, starts, dtype=np.int64)
            actions[at : at + len(q)] = np.add.reduceat(hit >> 1, starts, dtype=np.int64)
        mark[own] = 0
    return overlap, actions


def _near(a: Block, b: Block, i: np.ndarray, j: np.ndarray, cfg: DetectConfig) -> np.ndarray:
    """Whether sizes, bands and the query set allow a pair."""
    homes = lambda x, y, p, q: (x.home[p] >= 0) & (y.mask[q] >> np.maximum(x.home[p], 0) & 1 == 1)
    keep = homes(a, b, i, j) | homes(b, a, j, i)
    if cfg.exact_size:
        keep &= np.minimum(a.size[i], b.size[j]) * 100 >= np.maximum(a.size[i], b.size[j]) * cfg.gamma_pct
    return keep & ((a.asked[i] | b.asked[j]) == 1) & (a.ids[i] != b.ids[j])


def share_of(x: np.ndarray, y: np.ndarray, overlap: np.ndarray, denom: str) -> np.ndarray:
    return {"min": lambda: np.minimum(x, y), "max": lambda: np.maximum(x, y), "union": lambda: x + y - overlap, "count": lambda: np.full(len(x), 100)}[denom]()


def over(x: np.ndarray, y: np.ndarray, overlap: np.ndarray, cfg: DetectConfig) -> np.ndarray:
    """Which pairs are above the threshold; with ``query`` as denominator either direction will do."""
    if cfg.denom == "query":
        x = np.minimum(x, y)
        return 100 * overlap >= cfg.theta_pct * x if cfg.inclusive else 100 * overlap > cfg.theta_pct * x
    share = share_of(x, y, overlap, cfg.denom) * cfg.theta_pct
    return 100 * overlap >= share if cfg.inclusive else 100 * overlap > share


def matched(a: Block, b: Block, same: bool, cfg: DetectConfig, prefix: bool, threshold: bool) -> Iterator[tuple[np.ndarray, ...]]:
    """Places in both blocks and overlaps of the pairs that meet (and pass), with prefixes also numbers of common actions; of a
    block with itself each pair once."""
    if not prefix:
        both = cfg.element == "action+pair"
        met = common(a, b, True if both else None)
        found = common(a, b, False) if both else met
        for at in range(0, len(a.ids), 256):
            i, j = np.nonzero(met[at : at + 256])
            i += at
            keep = _near(a, b, i, j, cfg)
            if same:
                keep &= i < j
            i, j = i[keep], j[keep]
            overlap = found[i, j].astype(np.int64)
            if threshold:
                keep = over(a.total[i], b.total[j], overlap, cfg)
                i, j, overlap = i[keep], j[keep], overlap[keep]
            yield i, j, overlap
        return
    small = cfg.denom == "min"
    i, j, *more = _passing(a, b, cfg, True if small else None)
    keep = over(a.total[i], b.total[j], more[0], cfg)
    if same:
        keep &= (i < j) | (a.total[i] < a.total[j]) if small else i < j
        keep &= (a.total[i] != a.total[j]) | (i < j)
    yield tuple(x[keep] for x in (i, j, *more))
    if small and not same:
        j, i, *more = _passing(b, a, cfg, False)
        keep = over(a.total[i], b.total[j], more[0], cfg)
        yield tuple(x[keep] for x in (i, j, *more))


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[Block, Block, bool]]:
    for batch in batches:
        for p, q, x, y in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), batch.column(1), batch.column(3), strict=True):
            yield _held(p, x), _held(q, y), p == q


_recent: dict[int, tuple[pa.Buffer, Block]] = {}


def _held(number: int, data: pa.BinaryScalar | pa.StringScalar) -> Block:
    """The block, unpacked once while it is among the last ones used in this process.  Tables of several runs may come
    here, so it is told by its bytes or its file."""
    raw = data.as_buffer()
    found = _recent.pop(number, None)
    if found is None or not found[0].equals(raw):
        found = None
        while len(_recent) >= (HELD if isinstance(data, pa.StringScalar) else 3):
            _recent.pop(next(iter(_recent)))
        found = (pa.py_buffer(raw.to_pybytes()), _opened(data))
    _recent[number] = found  # the last one used is the last one to go
    return found[1]


def _opened(data: pa.BinaryScalar | pa.StringScalar) -> Block:
    if isinstance(data, pa.StringScalar):
        store, path = _store(data.as_py())
        with store.open_input_stream(path) as file:
            packed = file.read_buffer()
    else:
        packed = data.as_buffer()
    return pickle.loads(pa.CompressedInputStream(pa.BufferReader(packed), "zstd").read())


def _pairs(batches: Iterator[pa.RecordBatch], cfg: DetectConfig, prefix: bool, threshold: bool, keep: Sequence[str] = (), shared: bool = False, forest: bool = False) -> Iterator[pa.RecordBatch]:
    names = ["left_id", "right_id", "overlap", "left_total", "right_total"] + ["common"] * shared
    for a, b, same in _blocks(batches):
        both = pa.concat_tables([a.kept, b.kept]).combine_chunks() if keep else None
        roots: dict[int, int] = {}
        for i, j, overlap, *common in matched(a, b, same, cfg, prefix, threshold):
            if forest:
                new = _links(a.ids[i], b.ids[j], roots)
                i, j, overlap, *common = (x[new] for x in (i, j, overlap, *common))
            for at in range(0, len(i), 20_000):
                x, y = i[at : at + 20_000], j[at : at + 20_000]
                p, q, s, t = a.ids[x], b.ids[y], a.total[x], b.total[y]
                first = p < q
                out = [np.where(first, p, q), np.where(first, q, p), overlap[at : at + 20_000], np.where(first, s, t), np.where(first, t, s), *(c[at : at + 20_000] for c in common[:shared])]
                out = [pa.array(v) for v in out]
                if keep:
                    y = y + len(a.ids)
                    for side in (np.where(first, x, y), np.where(first, y, x)):
                        out += [c.combine_chunks() for c in both.take(side).columns]
                yield pa.RecordBatch.from_arrays(out, names + [f"{s}_{k}" for s in "lr"[: 2 * bool(keep)] for k in keep])


def _links(p: np.ndarray, q: np.ndarray, roots: dict[int, int]) -> np.ndarray:
    """Places of the pairs that join two trees of the forest ``roots``, which takes them in."""

    def root(x: int) -> int:
        while (up := roots.setdefault(x, x)) != x:
            roots[x] = x = roots[up]
        return x

    out = []
    for k, (x, y) in enumerate(zip(p.tolist(), q.tolist(), strict=True)):
        if (x := root(x)) != (y := root(y)):
            roots[max(x, y)] = min(x, y)
            out.append(k)
    return np.array(out, np.int64)


def _joining(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    roots: dict[int, int] = {}
    for batch in batches:
        new = _links(*(batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1)), roots)
        yield pa.RecordBatch.from_arrays([c.take(pa.array(new)) for c in batch.columns], batch.schema.names)


def forest_of(pairs: DataFrame) -> DataFrame:
    """left_id, right_id of as many pairs of each partition as connect the same fragments: fewer than it has fragments."""
    return pairs.select("left_id", "right_id").mapInArrow(_joining, "left_id long, right_id long")


def _tally(batches: Iterator[pa.RecordBatch], cfg: DetectConfig, code: Callable, prefix: bool) -> Iterator[pa.RecordBatch]:
    counts: dict[int, int] = {}
    for a, b, same in _blocks(batches):
        for i, j, overlap, *_ in matched(a, b, same, cfg, prefix, False):
            tagged = (a.tag[i] == b.tag[j]) & (a.tag[i] != -1)
            for k, n in zip(*np.unique(code(overlap, a.total[i], b.total[j], a.size[i], b.size[j], tagged), return_counts=True), strict=True):
                counts[int(k)] = counts.get(int(k), 0) + int(n)
    yield pa.RecordBatch.from_arrays([pa.array(list(counts), pa.int64()), pa.array(list(counts.values()), pa.int64())], ["code", "n"])


def overlaps(banded: DataFrame, cfg: DetectConfig, queries: DataFrame | None = None, prefix: bool = False, threshold: bool = False, keep: Sequence[str] = (), shared: bool = False, forest: bool = False) -> DataFrame:
    """left_id < right_id, overlap, left_total, right_total of all pairs that share an element in a band; with ``threshold``
    those above it.

    ``keep`` names columns of the fragments to come along as l_<column> and r_<column>.  With ``prefix``, ``shared`` adds
    common, the number of actions that both have.  ``forest`` leaves of each two blocks' pairs only as many as connect
    the same fragments.
    """
    if shared and not prefix:
        raise ValueError("common actions are counted in a search by prefixes")
    met = block_pairs(packed(banded, cfg.element, queries, prefix=prefix, keep=keep), cfg.gamma_pct if cfg.exact_size else None)
    kinds = {f.name: f.dataType.simpleString() for f in banded.schema}
    return pairs_of(met, cfg, "".join(f", `{s}_{k}` {kinds[k]}" for s in "lr" for k in keep), prefix=prefix, threshold=threshold, keep=tuple(keep), shared=shared, forest=forest)


def pairs_of(met: DataFrame, cfg: DetectConfig, more: str = "", **how) -> DataFrame:
    """The pairs of fragments of blocks that meet; ``more`` is the schema of the columns that come along."""
    return met.mapInArrow(partial(_pairs, cfg=cfg, **how), PAIRS + ", common long" * how.get("shared", False) + more)


def tally(banded: DataFrame, cfg: DetectConfig, code: Callable, queries: DataFrame | None = None, tag: str | None = None, prefix: bool = False) -> DataFrame:
    """code, n: how many pairs that share an element have each value of ``code``, a function of arrays (overlap, both totals,
    both sizes, whether the tags are equal) to whole numbers.  No pair leaves its task.  With ``prefix`` only pairs above the
    threshold are counted, and searched for by prefixes."""
    met = block_pairs(packed(banded, cfg.element, queries, tag, prefix=prefix), cfg.gamma_pct if cfg.exact_size else None)
    return met.mapInArrow(partial(_tally, cfg=cfg, code=code, prefix=prefix), "code long, n long").groupBy("code").agg(F.sum("n").alias("n"))
