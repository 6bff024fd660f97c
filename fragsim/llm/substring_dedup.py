"""Substring deduplication with a log-structured fingerprint index.

Batches of documents arrive in rising order of identifiers, so history always holds the smaller ones.  A
window of 50 words is filed under its *anchor*, the 8-word gram inside it with the smallest hash; equal
windows have equal anchors, and one anchor in about 22 words stands for all windows.  The neighbouring
windows of one anchor are a *block*.  An entry of the index is (anchor hash, digest of the block's words,
smallest identifier); a *run* holds the new entries of one batch, sorted by anchor and immutable.

``add`` merge-joins a batch with the runs of history by anchor and verifies what meets:

* a block whose words history has, or a smaller document of the batch, goes as a whole;
* where blocks of one anchor differ (the edges of passages), their windows are read again, one
  representative per block, from the batch and from history, and compared window by window.

Anchors only propose.  What decides is a 128-bit BLAKE2b digest of the words themselves, joined by single
spaces: of a whole block or of a whole window.  Then the batch's new entries are flushed as a run; as soon as a
level has ``FANOUT`` runs, they are merged into one of the next level.  The result does not depend on the
number of batches.  Windows are judged on the input, not on what is left of it.

Entries take a few bytes per 22 words; repeats are combined on the map side before any shuffle, and blocks
that very many documents have are dealt over parts of a join.  Texts are moved once, to meet the ranges
that go, and before only to read edges again.

Defined results: a null text has no words; texts shorter than a window lose nothing; rows that repeat an
identifier are judged each by its own text and are not smaller than one another; a null identifier counts
as the smallest number; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import partial, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import HOT_ROWS, drop_path, key_filter, may_have, persist, scratch, spread_join, temporary
from .words import NOT_BLANK, Words, chunks, mix, split_words, spread, word_hashes

WINDOW, GRAM = 50, 8
#: Runs of one level that are merged into one of the next.
FANOUT = 2
_ENTRY = "h long, block binary, first_id long"


def _window_sums(hashes: np.ndarray, width: int, salt: int) -> np.ndarray:
    """Hash of the ``width`` words that start at each word (the last ones run past the end and are unused)."""
    out = np.zeros(len(hashes), np.uint64)
    salted = mix(hashes + np.uint64(salt))
    # Horner's rule by doubling: value(2n) = value(n) * b**n + value(n) shifted by n.
    base = np.full(1, 0xD6E8FEB86659FD93, np.uint64)
    power, have, done = base, salted, 0
    width_left, piece_len = width, 1
    shifted = lambda x, n: np.concatenate([x[n:], np.zeros(min(n, len(x)), np.uint64)])
    while width_left:
        if width_left & 1:
            out = out * power + shifted(have, done)
            done += piece_len
        width_left >>= 1
        if width_left:
            have = have * power + shifted(have, piece_len)
            power, piece_len = power * power, piece_len * 2
    return mix(out)


def _window_starts(words: Words, width: int) -> np.ndarray:
    """True where a whole window of its document starts."""
    ok = np.zeros(len(words.start), bool)
    sizes = np.diff(words.first)
    place = np.arange(len(ok)) - np.repeat(words.first[:-1], sizes)
    ok[:] = place + width <= np.repeat(sizes, sizes)
    return ok


def _anchors(words: Words, hashes: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(window starts, place of each window's anchor gram, gram hashes)."""
    grams = _window_sums(hashes, gram, 1)
    starts = np.flatnonzero(_window_starts(words, window))
    span = window - gram + 1
    # Sliding minimum over `span` grams by doubling; ties go to the leftmost since places break them.
    low = grams.copy()
    where = np.arange(len(grams))
    have = 1
    while have < span:
        step = min(have, span - have)
        other, at = low[step:], where[step:]
        better = other < low[: len(other)]
        low = np.concatenate([np.where(better, other, low[: len(other)]), low[len(other) :]])
        where = np.concatenate([np.where(better, at, where[: len(at)]), where[len(at) :]])
        have += step
    return starts, where[starts], grams


class _Spelled:
    """Words of a chunk as one run of bytes with single spaces, to digest any range of words."""

    def __init__(self, words: Words) -> None:
        size = words.end - words.start
        self.start = np.cumsum(size + 1) - (size + 1)
        self.end = self.start + size
        plain = np.full(int(size.sum()) + len(size), 0x20, np.uint8)
        plain[spread(self.start, size)] = words.data[spread(words.start, size)]
        self.data = memoryview(plain)

    def digests(self, lo: np.ndarray, hi: np.ndarray) -> list[bytes]:
        """Digests of the words lo .. hi - 1 of each range."""
        data, blake = self.data, hashlib.blake2b
        return [blake(data[a:b], digest_size=16).digest() for a, b in zip(self.start[lo].tolist(), self.end[hi - 1].tolist(), strict=True)]


def _blocks(words: Words, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first start, number of windows, anchor hash) of every block."""
    starts, where, grams = _anchors(words, word_hashes(words), window, gram)
    new = np.ones(len(starts), bool)
    new[1:] = (where[1:] != where[:-1]) | (starts[1:] != starts[:-1] + 1)
    first = np.flatnonzero(new)
    return starts[first], np.diff(np.append(first, len(starts))), grams[where[first]]


def _block_rows(batches: Iterator[pa.RecordBatch], window: int, gram: int) -> Iterator[pa.RecordBatch]:
    """h (anchor), block (digest), id, mark, span (first start * 2**16 + windows)."""
    for batch in batches:
        for at, data, offsets in chunks(batch.column(2)):
            words = split_words(data, offsets, NOT_BLANK, lower=False)
            lo, count, anchor = _blocks(words, window, gram)
            digests = _Spelled(words).digests(lo, lo + count - 1 + window)
            document = np.searchsorted(words.first, lo, "right") - 1
            own = [batch.column(i).slice(at, len(offsets) - 1).take(pa.array(document)) for i in (0, 1)]
            span = (lo - words.first[document]) * 65536 + count
            yield pa.RecordBatch.from_arrays([pa.array(anchor.view(np.int64)), pa.array(digests, pa.binary()), *own, pa.array(span)], ["h", "block", "id", "mark", "span"])


def _window_rows(batches: Iterator[pa.RecordBatch], window: int, gram: int) -> Iterator[pa.RecordBatch]:
    """w (digest), id, mark, place of the windows in the row's wanted blocks."""
    for batch in batches:
        for at, data, offsets in chunks(batch.column(2)):
            n = len(offsets) - 1
            words = split_words(data, offsets, NOT_BLANK, lower=False)
            lo, count, _ = _blocks(words, window, gram)
            spelled = _Spelled(words)
            document = np.searchsorted(words.first, lo, "right") - 1
            wanted = [set(x) for x in batch.column(3).slice(at, n).to_pylist()]
            take = [d in wanted[k] for d, k in zip(spelled.digests(lo, lo + count - 1 + window), document.tolist(), strict=True)]
            take = np.array(take, bool)
            starts, document = spread(lo[take], count[take]), np.repeat(document[take], count[take])
            own = [batch.column(i).slice(at, n).take(pa.array(document)) for i in (0, 1)]
            place = (starts - words.first[document]).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(spelled.digests(starts, starts + window), pa.binary()), *own, pa.array(place)], ["w", "id", "mark", "place"])


def _kept(batches: Iterator[pa.RecordBatch], window: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids, texts, gone = batch.columns
        n_words, n_removed, kept_texts, digests = [], [], [], []
        for text, runs in zip(texts, gone, strict=True):
            words = (text.as_py() or "").encode().split()
            runs = runs.as_py() or []
            if runs:
                covered = np.zeros(len(words) + 1, np.int64)
                spans = np.array(runs)
                pairs = np.stack([spans // 65536, spans // 65536 + spans % 65536 - 1 + window], axis=1)
                np.add.at(covered, pairs[:, 0], 1)
                np.add.at(covered, pairs[:, 1], -1)
                gone_flags = np.cumsum(covered[:-1]) > 0
                left = [w for w, g in zip(words, gone_flags.tolist(), strict=True) if not g]
            else:
                left = words
            kept = b" ".join(left)
            n_words.append(len(words))
            n_removed.append(len(words) - len(left))
            digests.append(hashlib.sha256(kept).hexdigest())
            kept_texts.append(kept)
        yield pa.RecordBatch.from_arrays([ids, pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(digests, pa.string()), pa.array(kept_texts, pa.binary()).cast(pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256", "kept_text"])


class FingerprintIndex:
    """Levels of sorted immutable runs of entries; ``add`` takes batches of rising identifiers."""

    def __init__(self, spark: SparkSession, window: int = WINDOW, gram: int = GRAM, root: str | None = None) -> None:
        if not 1 <= gram <= window:
            raise ValueError("the gram must fit into the window")
        self.spark, self.window, self.gram = spark, window, gram
        self.root = root or scratch(spark, "anchors")
        self.levels: list[list[str]] = []
        self.written = 0

    def entries(self, runs: list[str] | None = None) -> DataFrame:
        paths = [p for level in self.levels for p in level] if runs is None else runs
        return self.spark.read.schema(_ENTRY).parquet(*paths) if paths else self.spark.createDataFrame([], _ENTRY)

    def _write(self, entries: DataFrame, level: int) -> None:
        """Write a run; a full level is merged into the next (no two runs share an entry)."""
        path = f"{self.root}/run-{self.written:05d}"
        self.written += 1
        entries.repartition("h", "block").sortWithinPartitions("h", "block").write.parquet(path)
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(path)
        if len(self.levels[level]) >= FANOUT:
            full, self.levels[level] = self.levels[level], []
            self._write(self.entries(full), level + 1)
            for old in full:
                drop_path(self.spark, old)

    def add(self, batch: DataFrame, known: DataFrame, after: int | None = None) -> DataFrame:
        """Removals id, mark, span of a batch (id, mark, text) whose identifiers are all larger than ``after``, the
        largest before; ``known`` holds the documents so far, the batch included.  The batch then belongs to history."""
        removed = scratch(self.spark, "removed")
        with temporary(self.spark):
            self._removals(batch, known, after).write.parquet(removed)
            self._write(self.fresh, 0)
        return self.spark.read.schema("id long, mark long, span long").parquet(removed)

    def _removals(self, batch: DataFrame, known: DataFrame, after: int | None) -> DataFrame:
        cut = partial(_block_rows, window=self.window, gram=self.gram)
        blocks = persist(batch.mapInArrow(cut, "h long, block binary, id long, mark long, span long"), "blocks")
        classes = persist(blocks.groupBy("h", "block").agg(F.min("id").alias("first_id"), F.max("id").alias("last_id"), F.count("*").alias("n")), "classes")
        anchors = classes.groupBy("h").agg(F.count("*").alias("n"))
        crowded = anchors.where(F.col("n") > HOT_ROWS).select("h")
        met = persist(spread_join(self.entries(), anchors.select("h"), ["h"], crowded, "left_semi"), "met")
        older = met.select("h", "block", F.col("first_id").alias("old_id"))
        judged = persist(classes.join(older, ["h", "block"], "left"), "judged")
        self.fresh = judged.where("old_id is null").select("h", "block", "first_id")
        # Whole blocks that an older or smaller document has.
        again = judged.withColumn("first_id", F.coalesce("old_id", "first_id")).where("first_id < last_id")
        hot = again.where(F.col("n") > HOT_ROWS).select("h", "block")
        whole = spread_join(blocks, again.select("h", "block", "first_id"), ["h", "block"], hot).where("id > first_id").select("id", "mark", "span")
        # Edges of passages: anchors with a new block beside others; one representative of each.
        sides = self.fresh.withColumn("new", F.lit(1)).unionByName(met.withColumn("new", F.lit(0)))
        edges = sides.groupBy("h").agg(F.count("*").alias("n"), F.max("new").alias("new")).where("n > 1 and new = 1").select("h")
        wanted = persist(spread_join(sides, edges, ["h"], crowded, "left_semi").groupBy(F.col("first_id").alias("id")).agg(F.collect_set("block").alias("blocks")), "wanted")
        texts = may_have(known, key_filter(wanted, F.col("id")), F.col("id")).where("_maybe").join(wanted, "id").select("id", "mark", "text", "blocks")
        windows = persist(texts.mapInArrow(partial(_window_rows, window=self.window, gram=self.gram), "w binary, id long, mark long, place long"), "windows")
        first = persist(windows.groupBy("w").agg(F.min("id").alias("first_id"), F.max("id").alias("last_id"), F.count("*").alias("n")).where("first_id < last_id"), "first")
        hot = first.where(F.col("n") > HOT_ROWS).select("w")
        single = spread_join(windows, first.select("w", "first_id"), ["w"], hot).where("id > first_id")
        # What history loses was decided when it came; its windows only stand on the older side here.
        single = single if after is None else single.where(F.col("id") > after)
        return whole.unionByName(single.select("id", "mark", (F.col("place") * 65536 + 1).alias("span")))


def remove_repeats(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, batches: int = 3, id_col: str = "doc_id", text_col: str = "text", keep_text: bool = True) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 and (optionally) kept_text of every row.

    ``batches`` splits the input into that many ranges of identifiers of about equal counts, added one after
    the other.
    """
    floor = -(1 << 63)
    own = F.col(id_col).cast("long")
    rows = docs.select(own.alias("doc_id"), F.coalesce(own, F.lit(floor)).alias("id"), F.xxhash64(text_col).alias("mark"), F.col(text_col).alias("text"))
    known = rows.select("id", "mark", "text")
    index = FingerprintIndex(docs.sparkSession, window, gram)
    shares = [i / batches for i in range(1, batches)]
    cuts = rows.agg(F.percentile_approx("id", shares or [0.5])).first()[0] if shares else []
    cuts = sorted(set(cuts or []))
    removed = []
    for low, high in zip([None, *cuts], [*cuts, None], strict=True):
        upto = known if high is None else known.where(F.col("id") <= high)
        batch = upto if low is None else upto.where(F.col("id") > low)
        removed.append(index.add(batch, upto, low))
    drop_path(docs.sparkSession, index.root)
    gone = persist(reduce(DataFrame.unionByName, removed).groupBy("id", "mark").agg(F.collect_set("span").alias("gone")), "gone")
    # Documents that certainly lose nothing need no join; only the others are moved.
    marked = may_have(rows, key_filter(gone, F.col("id")), F.col("id"))
    intact = marked.where("not _maybe").select("doc_id", "text", F.lit(None).cast("array<long>").alias("gone"))
    moved = marked.where("_maybe").join(gone, ["id", "mark"], "left").select("doc_id", "text", "gone")
    out = intact.unionByName(moved)
    out = out.mapInArrow(partial(_kept, window=window), "doc_id long, n_words long, n_removed long, kept_sha256 string, kept_text string")
    return out if keep_text else out.drop("kept_text")
