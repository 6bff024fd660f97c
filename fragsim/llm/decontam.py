"""Benchmark decontamination with suffix arrays over training shards.

The training text of a shard (a few megabytes of whole documents) becomes a sequence of word numbers, and
its suffixes that can match anything are sorted into a suffix array, as deep as a window.  Only suffixes
whose first words start some test suffix are kept, which loses nothing: a match of two or more words
starts with such a pair.  Every different test suffix is then located by two binary searches; the run
between them holds all occurrences of its window (a shorter item is a prefix of its run).

Longer matches are chains of windows that advance together in the document and in an item.  One row of
chain lengths, indexed by test word, is carried from each hit to the next, so the longest verbatim match
of every hit span and both its places are found without listing pairs of places.

Word numbers are those of the test vocabulary (0 for any other word), found through 64-bit hashes; the
bytes of every matched word are compared before it counts.  The test set is indexed once and broadcast;
above ``SLICE_BYTES`` of test text it is cut into slices, the documents are scanned once for each, and the
findings meet by row number.  A scan has no shuffle.

Defined results: null texts and texts without words have no words and no hits; test items without words
have no windows; rows that repeat an identifier are scanned each, whatever their texts; identical test
items all count; of equally long matches in a span the first in the document, then the first item, is
shown; an empty table or an empty test set gives no hits; other columns are ignored by ``scan`` and kept by
``flag``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, StructType

from .common import numbered, unused
from .words import ALPHANUMERIC, Words, chunks, same_bytes, split_words, spread, word_hashes

WINDOW = 10
#: Bytes of test text that are indexed and broadcast at once; larger test sets are scanned in slices.
SLICE_BYTES = 16 << 20

_SPAN = pa.struct([("start", pa.int64()), ("stop", pa.int64())])
_MATCH = pa.struct([("item_id", pa.string()), ("item_word", pa.int64()), ("doc_word", pa.int64()), ("length", pa.int64())])
_FOUND = "n_words long, spans array<struct<start:long,stop:long>>, items array<string>, matches array<struct<item_id:string,item_word:long,doc_word:long,length:long>>"


def _joined(parts: list[Words]) -> Words:
    """Words of all chunks as one."""
    bytes_before = np.cumsum([0, *(len(w.data) for w in parts)])
    words_before = np.cumsum([0, *(len(w.start) for w in parts)])
    return Words(
        np.concatenate([np.zeros(0, np.uint8), *(w.data for w in parts)]),
        np.concatenate([np.zeros(0, np.int64), *(w.start + b for w, b in zip(parts, bytes_before, strict=False))]),
        np.concatenate([np.zeros(0, np.int64), *(w.end + b for w, b in zip(parts, bytes_before, strict=False))]),
        np.concatenate([np.zeros(1, np.int64), *(w.first[1:] + b for w, b in zip(parts, words_before, strict=False))]),
    )


class TestSuffixes:
    """Windows of the test items as packed keys over the test vocabulary; built once and broadcast."""

    __test__ = False

    def __init__(self, items: list[tuple[str, str]], window: int = WINDOW) -> None:
        items = sorted((str(k), t or "") for k, t in items)
        self.names, self.window = [k for k, _ in items], window
        self.words = words = _joined([split_words(data, offsets, ALPHANUMERIC, lower=True) for _, data, offsets in chunks(pa.array([t for _, t in items], pa.large_string()))])
        count, item_size = len(words.start), np.diff(words.first)
        for salt in range(8):
            self.salt = salt
            self.vocabulary, self.speller, number = np.unique(word_hashes(words, salt), return_index=True, return_inverse=True)
            if same_bytes(words, np.arange(count), words, self.speller[number]).all():
                break
        else:
            raise RuntimeError("different test words share their hashes")
        self.bits = max(1, int(len(self.vocabulary) + 1).bit_length())
        self.per_key = max(1, 64 // self.bits)
        self.owner = np.repeat(np.arange(len(item_size)), item_size)
        # A window starts where ten words are left, or at the first word of a shorter item.
        place = np.arange(count) - words.first[:-1][self.owner]
        left = item_size[self.owner] - place
        keep = (left >= window) | ((place == 0) & (left < window))
        at, size = np.flatnonzero(keep), np.minimum(window, left[keep])
        ids = np.concatenate([number.astype(np.uint64) + np.uint64(1), np.zeros(window + 1, np.uint64)])
        keys = self.pack(ids, at, size)
        order = np.lexsort((at, keys))
        #: Test words at which windows start, by key; those of different window u are at[bounds[u]:bounds[u + 1]].
        self.at = at[order]
        self.keys, first = np.unique(keys[order], return_index=True)
        self.bounds = np.append(first, len(at))
        self.size = size[order][first]
        self.top = self.pack(ids, self.at[first], self.size, fill=(1 << self.bits) - 1)
        # Heads: the first two words of each window (or the only one).
        start = self.at[first]
        self.heads = np.unique(ids[start] << np.uint64(32) | np.where(self.size > 1, ids[start + 1], np.uint64(0)))
        self.single = bool((self.size == 1).any())

    def pack(self, ids: np.ndarray, at: np.ndarray, size: np.ndarray | int, fill: int = 0) -> np.ndarray:
        """Big-endian keys of the words ids[at : at + size], ``fill`` beyond; they sort as word sequences."""
        columns = -(-self.window // self.per_key)
        out = np.zeros((len(at), columns), ">u8")
        for c in range(columns):
            value = np.zeros(len(at), np.uint64)
            for k in range(self.per_key):
                j = c * self.per_key + k
                value <<= np.uint64(self.bits)
                if j < self.window:
                    value |= np.where(j < size, ids[at + j], np.uint64(fill))
            out[:, c] = value
        return np.ascontiguousarray(out).view(f"S{8 * columns}").ravel()

    def owners(self, window: int) -> list[str]:
        return [self.names[o] for o in np.unique(self.owner[self.at[self.bounds[window] : self.bounds[window + 1]]])]


@dataclass
class Shard:
    """Suffix array of a chunk of documents: keys in order and the words where the suffixes start."""

    keys: np.ndarray
    at: np.ndarray
    number: np.ndarray


def suffix_array(tests: TestSuffixes, words: Words) -> Shard:
    """Sorted suffixes that start like some test suffix; none runs over the end of its document."""
    hashes = word_hashes(words, tests.salt)
    count = len(hashes)
    if not len(tests.vocabulary):
        return Shard(tests.keys, np.zeros(0, np.int64), np.zeros(count, np.uint64))
    entry = np.minimum(np.searchsorted(tests.vocabulary, hashes), len(tests.vocabulary) - 1)
    number = np.where(tests.vocabulary[entry] == hashes, entry + 1, 0).astype(np.uint64)
    # A zero after every document and a window of zeros at the end.
    slot = np.arange(count) + np.repeat(np.arange(len(words.first) - 1), np.diff(words.first))
    ids = np.zeros(count + len(words.first) + tests.window, np.uint64)
    ids[slot] = number
    at = np.flatnonzero(number)
    pair = number[at] << np.uint64(32)
    known = np.isin(pair | ids[slot[at] + 1], tests.heads)
    if tests.single:
        known |= np.isin(pair, tests.heads)
    at = at[known]
    keys = tests.pack(ids, slot[at], tests.window)
    order = np.argsort(keys, kind="stable")
    return Shard(keys[order], at[order], number)


def occurrences(tests: TestSuffixes, words: Words) -> tuple[np.ndarray, np.ndarray]:
    """(different test window, first word in the chunk) of every occurrence, bytes compared, in text order."""
    shard = suffix_array(tests, words)
    low, high = np.searchsorted(shard.keys, tests.keys, "left"), np.searchsorted(shard.keys, tests.top, "right")
    runs = np.maximum(high - low, 0)
    window, first = np.repeat(np.arange(len(runs)), runs), shard.at[spread(low, runs)]
    # Words inside some occurrence must be spelt like the vocabulary's.
    change = np.zeros(len(words.start) + 1, np.int64)
    np.add.at(change, first, 1)
    np.add.at(change, first + tests.size[window], -1)
    inside = np.flatnonzero(np.cumsum(change)[:-1])
    bad = np.zeros(len(words.start) + 1, np.int64)
    bad[inside + 1] = ~same_bytes(words, inside, tests.words, tests.speller[shard.number[inside].astype(np.int64) - 1])
    bad = np.cumsum(bad)
    good = bad[first + tests.size[window]] == bad[first]
    order = np.lexsort((window[good], first[good]))
    return window[good][order], first[good][order]


class Chains:
    """Longest matches of a chunk's hit spans, by one row of chain lengths over the test words."""

    def __init__(self, tests: TestSuffixes) -> None:
        self.tests = tests
        self.length = np.zeros(len(tests.owner) + 1, np.int64)
        self.seen = np.full(len(tests.owner) + 1, -2, np.int64)
        self.base = 0

    def longest(self, window: np.ndarray, first: np.ndarray, span: np.ndarray) -> dict[int, tuple[int, int, int]]:
        """Per span: (length, first word in the chunk, first test word)."""
        tests, best = self.tests, {}
        for u, f, s in zip(window.tolist(), first.tolist(), span.tolist(), strict=True):
            to = tests.at[tests.bounds[u] : tests.bounds[u + 1]]
            n = int(tests.size[u])
            if n < tests.window:
                found = (n, f, int(to[0]))
            else:
                chain = np.where((self.seen[to - 1] == self.base + f - 1) & (tests.owner[to - 1] == tests.owner[to]), self.length[to - 1], 0) + 1
                self.length[to], self.seen[to] = chain, self.base + f
                k = int(chain.argmax())
                found = (n + int(chain[k]) - 1, f - int(chain[k]) + 1, int(to[k]) - int(chain[k]) + 1)
            have = best.get(s)
            if have is None or (-found[0], *found[1:]) < (-have[0], *have[1:]):
                best[s] = found
        return best

    def next_chunk(self, n_words: int) -> None:
        self.base += n_words + 2


def _findings(words: Words, chains: Chains) -> tuple[list, list, list]:
    """Spans, items and longest matches of every document of a chunk."""
    tests, n = chains.tests, len(words.first) - 1
    spans: list[list] = [[] for _ in range(n)]
    items: list[list] = [[] for _ in range(n)]
    matches: list[list] = [[] for _ in range(n)]
    window, first = occurrences(tests, words)
    if len(first):
        change = np.zeros(len(words.start) + 1, np.int64)
        np.add.at(change, first, 1)
        np.add.at(change, first + tests.size[window], -1)
        hit = np.cumsum(change)[:-1] > 0
        start = hit.copy()
        start[1:] &= ~hit[:-1]
        heads = words.first[:-1][np.diff(words.first) > 0]
        start[heads] |= hit[heads]  # a span ends with its document
        span = (np.cumsum(start) - 1)[first]
        lo = np.flatnonzero(start)
        document = np.searchsorted(words.first, lo, "right") - 1
        stop = np.append(lo[1:], len(hit))
        stop = np.array([a + int(np.argmin(h)) if not (h := hit[a:b]).all() else b for a, b in zip(lo, stop, strict=True)])
        stop = np.minimum(stop, words.first[document + 1])
        best = chains.longest(window, first, span)
        for s, (a, b, d) in enumerate(zip(lo.tolist(), stop.tolist(), document.tolist(), strict=True)):
            at, (length, f, t) = int(words.first[d]), best[s]
            spans[d].append({"start": a - at, "stop": b - at})
            owner = int(tests.owner[t])
            matches[d].append({"item_id": tests.names[owner], "item_word": t - int(tests.words.first[owner]), "doc_word": f - at, "length": length})
        pairs = np.unique(np.stack([document[span], window]), axis=1)
        for d in np.unique(pairs[0]).tolist():
            items[d] = sorted({name for u in pairs[1][pairs[0] == d] for name in tests.owners(int(u))})
    chains.next_chunk(len(words.start))
    return spans, items, matches


def _scan(batches: Iterator[pa.RecordBatch], shared) -> Iterator[pa.RecordBatch]:
    chains = Chains(shared.value)
    for batch in batches:
        for at, data, offsets in chunks(batch.column(1)):
            words = split_words(data, offsets, ALPHANUMERIC, lower=True)
            spans, items, matches = _findings(words, chains)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).slice(at, len(spans)), pa.array(np.diff(words.first)), pa.array(spans, pa.list_(_SPAN)), pa.array(items, pa.list_(pa.string())), pa.array(matches, pa.list_(_MATCH))],
                ["doc_id", "n_words", "spans", "items", "matches"],
            )


def _flag(batches: Iterator[pa.RecordBatch], shared, name: str) -> Iterator[pa.RecordBatch]:
    """Rows with a flag; the text comes last and goes."""
    tests = shared.value
    for batch in batches:
        own = batch.num_columns - 1
        for at, data, offsets in chunks(batch.column(own)):
            words = split_words(data, offsets, ALPHANUMERIC, lower=True)
            hit = np.zeros(len(offsets) - 1, bool)
            hit[np.searchsorted(words.first, occurrences(tests, words)[1], "right") - 1] = True
            yield pa.RecordBatch.from_arrays([*(batch.column(i).slice(at, len(hit)) for i in range(own)), pa.array(hit)], [*batch.schema.names[:own], name])


def _shared_slices(tests: DataFrame, window: int, item_col: str, text_col: str, limit: int) -> list:
    """Broadcast indexes of the slices, each of about ``limit`` bytes of test text."""
    total = tests.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    n = max(1, -(-total // limit))
    rows = tests.select(F.col(item_col).cast("string"), F.col(text_col))
    parts = [rows.where(F.pmod(F.xxhash64(*rows.columns), F.lit(n)) == i) if n > 1 else rows for i in range(n)]
    return [tests.sparkSession.sparkContext.broadcast(TestSuffixes([(r[0], r[1]) for r in part.collect()], window)) for part in parts]


def flag(docs: DataFrame, tests: DataFrame, name: str, window: int = WINDOW, text_col: str = "text", item_col: str = "item_id", slice_bytes: int = SLICE_BYTES) -> DataFrame:
    """``docs`` with a flag ``name`` that is true where a test window occurs."""
    text, row = unused([*docs.columns, name], "_text", "_row")
    slices = _shared_slices(tests, window, item_col, text_col, slice_bytes)

    def flagged(rows: DataFrame, shared) -> DataFrame:
        schema = StructType([*rows.schema.fields]).add(name, BooleanType())
        return rows.select(*rows.columns, F.col(text_col).alias(text)).mapInArrow(partial(_flag, shared=shared, name=name), schema)

    if len(slices) == 1:
        return flagged(docs, slices[0])
    rows = numbered(docs, row)
    hits = reduce(DataFrame.unionByName, (flagged(rows, s).where(F.col(name)).select(row) for s in slices)).distinct()
    return rows.join(hits.withColumn(name, F.lit(True)), row, "left").withColumn(name, F.coalesce(name, F.lit(False))).select(*docs.columns, name)


def _merged_spans(spans: Column) -> Column:
    """Sorted spans with those that touch made one."""
    last = lambda acc: F.element_at(acc, -1)
    longer = lambda acc, s: F.struct(last(acc)["start"].alias("start"), F.greatest(last(acc)["stop"], s["stop"]).alias("stop"))
    add = lambda acc, s: F.when((F.size(acc) > 0) & (last(acc)["stop"] >= s["start"]), F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(longer(acc, s)))).otherwise(F.concat(acc, F.array(s)))
    return F.aggregate(F.array_sort(spans), F.expr("cast(array() as array<struct<start:long,stop:long>>)"), add)


def scan(docs: DataFrame, tests: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", slice_bytes: int = SLICE_BYTES) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated, longest (words of the longest match), spans (hit
    word ranges), items, matches (item_id, item_word, doc_word, length of the longest match of every span)."""
    slices = _shared_slices(tests, window, item_col, text_col, slice_bytes)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    if len(slices) == 1:
        out = rows.mapInArrow(partial(_scan, shared=slices[0]), f"doc_id long, {_FOUND}")
    else:
        rows = numbered(rows, "row")
        parts = [rows.select("row", "text").mapInArrow(partial(_scan, shared=s), f"doc_id long, {_FOUND}").withColumnRenamed("doc_id", "row") for s in slices]
        all_of = lambda c: F.flatten(F.collect_list(c))
        met = reduce(DataFrame.unionByName, parts).groupBy("row").agg(F.first("n_words").alias("n_words"), all_of("spans").alias("spans"), all_of("items").alias("items"), all_of("matches").alias("matches"))
        met = met.withColumn("spans", _merged_spans(F.col("spans"))).withColumn("items", F.array_sort(F.array_distinct("items")))
        ranked = F.transform("matches", lambda m: F.struct((-m["length"]).alias("neg"), m["doc_word"].alias("doc_word"), m["item_id"].alias("item_id"), m["item_word"].alias("item_word")))
        met = met.withColumn("ranked", ranked)
        first_of = lambda s: F.array_min(F.filter("ranked", lambda m: (m["doc_word"] >= s["start"]) & (m["doc_word"] < s["stop"])))
        best = F.transform("spans", lambda s: first_of(s))
        shown = lambda m: F.struct(m["item_id"].alias("item_id"), m["item_word"].alias("item_word"), m["doc_word"].alias("doc_word"), (-m["neg"]).alias("length"))
        met = met.withColumn("matches", F.transform(best, shown))
        out = rows.select("row", "doc_id").join(met, "row")
    n_hit = F.aggregate("spans", F.lit(0).cast("long"), lambda a, s: a + s["stop"] - s["start"])
    longest = F.coalesce(F.array_max(F.transform("matches", lambda m: m["length"])), F.lit(0).cast("long"))
    return out.select(
        "doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        (n_hit > 0).alias("contaminated"), longest.alias("longest"), "spans", "items", "matches",
    )
