"""SimHash near-duplicates by anchor-point covering.

A fingerprint has 64 bits.  Two that differ in at most three bits differ in at most one bit in the low
or in the high half, so each half is joined with threshold one.  The anchors of a half are the words of
the perfect [31, 26] Hamming code on 31 of its bits (the last bit is left out of the key, which only
adds candidates): its covering radius is one, so every half has one *home* anchor at distance one or
less, and any half within threshold one of it lies within radius plus threshold, two, of that anchor.
Every fingerprint is therefore replicated to the anchors within distance two of each half, 16 at most,
and compared per anchor with the fingerprints that are at home there; the whole 64 bits decide.

Equal fingerprints are collapsed before, so thousands of copies cost one row.  An anchor yields the
edges of a spanning forest of its links, never all pairs; anchors with very many homes are split into
salted parts that see all visitors.  Components come from star contraction on the cluster.

Defined results: null, empty and blank texts have no words and fingerprint zero, and are linked like any
other; repeated identifiers give repeated rows; an empty table gives an empty result; other columns are
ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import HOT_ROWS, persist, spread_join
from .components import connected_components

SHINGLE, SEED, THRESHOLD = 3, 42, 3
#: Homes of one anchor that one task compares with all its visitors.
HOT_ANCHOR = 4096
#: Split anchors are few; their list is broadcast up to this many rows and joined beyond.
MAX_BROADCAST_ROWS = 50_000
_LOWER = bytes(range(0x41)) + bytes(range(0x61, 0x7B)) + bytes(range(0x5B, 0x100))
_PIECE = 1 << 18


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """Majority vote of the XXH64 values of all word shingles, repeats included."""
    words = (text or "").encode().translate(_LOWER).split()
    if not words:
        return 0
    width = min(shingle, len(words))
    total = len(words) - width + 1
    votes = np.zeros(64, np.int64)
    for at in range(0, total, _PIECE):
        piece = words[at : min(at + _PIECE, total) + width - 1]
        joined = b" ".join(piece)
        lengths = np.fromiter(map(len, piece), np.int64, len(piece))
        ends = np.cumsum(lengths + 1) - 1
        cuts = zip((ends - lengths)[: len(piece) - width + 1].tolist(), ends[width - 1 :].tolist(), strict=True)
        digests = b"".join([xxhash.xxh64_digest(joined[a:b], SEED) for a, b in cuts])
        bits = np.unpackbits(np.frombuffer(digests, np.uint8).reshape(-1, 8), axis=1)
        votes += bits.sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(votes * 2 > total).tobytes(), "big", signed=True)


def _fingerprints(batches: Iterator[pa.RecordBatch], shingle: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        prints = [fingerprint(t.as_py(), shingle) for t in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints, pa.int64())], ["doc_id", "fp"])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """doc_id, fp (the fingerprint as a signed 64-bit number)."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text_col).mapInArrow(partial(_fingerprints, shingle=shingle), "doc_id long, fp long")


def _anchor_rows(prints: DataFrame) -> DataFrame:
    """anchor, fp, home: a row for each anchor within distance two of a half; home for the nearest one."""
    half = prints.select("fp", F.explode(F.array(F.lit(0), F.lit(1))).alias("h")).withColumn("x", F.expr("shiftrightunsigned(fp, 32 * h) & 2147483647L"))
    # Bit j of the syndrome is the parity of the positions 1..31 whose number has bit j.
    masks = [sum(1 << (p - 1) for p in range(1, 32) if p >> j & 1) for j in range(5)]
    syndrome = " + ".join(f"{1 << j} * (bit_count(x & {m}L) % 2)" for j, m in enumerate(masks))
    half = half.withColumn("s", F.expr(syndrome))
    at = lambda i: f"shiftleft(1L, {i} - 1)"
    home = f"CASE WHEN s = 0 THEN x ELSE x ^ {at('s')} END"
    others = f"transform(filter(sequence(1, 31), i -> s <> 0 AND i < (i ^ s)), i -> struct(x ^ {at('i')} ^ {at('(i ^ s)')} AS c, false AS home))"
    rows = half.select("fp", "h", F.expr(f"explode(concat(array(struct({home} AS c, true AS home)), {others}))").alias("a"))
    return rows.select(F.expr("shiftleft(cast(h as bigint), 40) | a.c").alias("anchor"), "fp", F.col("a.home").alias("home"))


def _forest(fp: np.ndarray, home: np.ndarray, threshold: int) -> list[tuple[int, int]]:
    """Edges of a spanning forest of the links between homes and all members of an anchor."""
    fp, index = np.unique(fp, return_inverse=True)
    is_home = np.zeros(len(fp), bool)
    is_home[index[home]] = True
    label = np.arange(len(fp))
    edges = []
    for i in np.flatnonzero(is_home):
        near = np.bitwise_count((fp ^ fp[i]).view(np.uint64)) <= threshold
        roots = np.unique(label[near])
        if len(roots) > 1:
            edges += [(int(fp[roots[0]]), int(fp[r])) for r in roots[1:]]
            label[np.isin(label, roots[1:])] = roots[0]
    return edges


def _compare(batches: Iterator[pa.RecordBatch], threshold: int) -> Iterator[pa.RecordBatch]:
    """Links within each anchor; rows come sorted by (anchor, salt)."""
    held: list[np.ndarray] = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, bool)]
    names = ["a", "b"]

    def links(anchor: np.ndarray, salt: np.ndarray, fp: np.ndarray, home: np.ndarray) -> pa.RecordBatch:
        new = np.flatnonzero((anchor[1:] != anchor[:-1]) | (salt[1:] != salt[:-1])) + 1
        bounds = np.concatenate([[0], new, [len(anchor)]])
        sizes = np.diff(bounds)
        found_a, found_b = [], []
        small = sizes <= 16
        group = np.repeat(np.arange(len(sizes)), sizes)
        light = small[group]
        for step in range(1, min(15, int(sizes[small].max(initial=1)) - 1) + 1):
            i = np.flatnonzero((group[step:] == group[:-step]) & light[step:] & (home[step:] | home[:-step]))
            near = i[(np.bitwise_count((fp[i] ^ fp[i + step]).view(np.uint64)) <= threshold) & (fp[i] != fp[i + step])]
            found_a.append(fp[near])
            found_b.append(fp[near + step])
        for g in np.flatnonzero(~small):
            part = slice(bounds[g], bounds[g + 1])
            edges = _forest(fp[part], home[part], threshold)
            found_a.append(np.array([a for a, _ in edges], np.int64))
            found_b.append(np.array([b for _, b in edges], np.int64))
        a, b = np.concatenate([*found_a, np.zeros(0, np.int64)]), np.concatenate([*found_b, np.zeros(0, np.int64)])
        pairs = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)]), axis=1) if len(a) else np.zeros((2, 0), np.int64)
        return pa.RecordBatch.from_arrays([pa.array(pairs[0]), pa.array(pairs[1])], names)

    for batch in batches:
        now = [np.concatenate([h, batch.column(i).to_numpy(zero_copy_only=False)]) for i, h in enumerate(held)]
        if not len(now[0]):
            continue
        last = (now[0] == now[0][-1]) & (now[1] == now[1][-1])
        cut = int(np.flatnonzero(last)[0])  # the last group may go on in the next batch
        held = [x[cut:] for x in now]
        if cut:
            yield links(*(x[:cut] for x in now))
    if len(held[0]):
        yield links(*held)


def links(prints: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """Edges a < b between different fingerprints of ``prints`` (one column fp, distinct) that connect
    exactly those joined by chains of links."""
    if threshold > 3:
        raise ValueError("two halves with threshold one cover at most three differing bits")
    rows = _anchor_rows(prints)
    homes = rows.where("home").groupBy("anchor").agg(F.count("*").alias("n")).where(F.col("n") > HOT_ANCHOR)
    hot = persist(homes, "hot-anchors")
    n_hot = hot.count()
    if n_hot:
        side = F.broadcast(hot) if n_hot <= MAX_BROADCAST_ROWS else hot
        rows = rows.join(side, "anchor", "left").withColumn("parts", F.ceil(F.coalesce("n", F.lit(1)) / HOT_ANCHOR).cast("int"))
        # A home is at home in one part and a visitor in the others.
        own = F.pmod(F.xxhash64("fp"), F.col("parts"))
        rows = rows.withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).withColumn("home", F.col("home") & (F.col("salt") == own))
    else:
        rows = rows.withColumn("salt", F.lit(0))
    rows = rows.select("anchor", F.col("salt").cast("long").alias("salt"), "fp", "home")
    dealt = rows.repartition("anchor", "salt").sortWithinPartitions("anchor", "salt")
    return dealt.mapInArrow(partial(_compare, threshold=threshold), "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, threshold: int = THRESHOLD) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest identifier reachable) of every row."""
    prints = persist(fingerprints(docs, id_col, text_col, shingle), "fingerprints")
    distinct = persist(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id"), F.count("*").alias("n")), "distinct")
    parts = connected_components(links(distinct.select("fp"), threshold))
    rooted = distinct.join(parts.withColumnRenamed("node", "fp"), "fp").select("fp", "root", "first_id")
    of_root = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"))
    linked = rooted.join(of_root, "root").select("fp", "component_id")
    owner = distinct.join(linked, "fp", "left").select("fp", F.coalesce("component_id", "first_id").alias("component_id"))
    out = spread_join(prints, owner, ["fp"], distinct.where(F.col("n") > HOT_ROWS))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
