"""Substring dedup by blocks of the suffix array, with ranks of a difference cover for long ties.

A string of `length` bytes that starts in two places is found by sorting the suffixes to that depth, one bucket of
suffixes at a time. Which bucket a suffix goes to is read off its first bytes: its anchor, the least hash among the
grams in its first `length` bytes. Equal strings have equal anchors, so they meet in one bucket; suffixes whose
anchor stands nowhere else cannot repeat and are never moved. Neighbouring suffixes mostly share their anchor: they
travel as one run of suffixes.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import utf8, written

GRAM = 64
#: Bytes of text that are hashed at once, and bytes of suffix text that are sorted at once.
PIECE, BUCKET = 1 << 20, 1 << 21
#: Runs of different text that share an anchor and are sorted in one task; beyond, suffixes are dealt out singly.
LARGEST = 4000
_POWERS: dict[int, list[np.ndarray]] = {}


def _tables() -> list[np.ndarray]:
    """For two hash bases: a value for each byte, the base's powers and those of its inverse, modulo 2^64."""
    if 0 not in _POWERS:
        r = np.random.default_rng(20240229)
        out = []
        for _ in range(2):
            base = int(r.integers(1, 1 << 62)) * 4 + 1
            inverse = pow(base, -1, 1 << 64)
            n = 2 * PIECE + 65536
            for b in (base, inverse):
                p = np.full(n, b, np.uint64)
                p[0] = 1
                out.append(np.multiply.accumulate(p))
            out.append(r.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1))
        _POWERS[0] = out
    return _POWERS[0]


def _mixed(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(32))
    h *= np.uint64(0x9E3779B97F4A7C15)
    return h ^ (h >> np.uint64(29))


def prefix_sums(x: np.ndarray, which: int) -> np.ndarray:
    powers, _, values = _tables()[3 * which : 3 * which + 3]
    return np.concatenate([np.zeros(1, np.uint64), np.cumsum(values[x] * powers[: len(x)], dtype=np.uint64)])


def span_hashes(sums: np.ndarray, start: np.ndarray, end: np.ndarray, which: int) -> np.ndarray:
    return _mixed((sums[end] - sums[start]) * _tables()[3 * which + 1][start])


def suffix_runs(x: np.ndarray, cuts: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """x: bytes of texts one after another; cuts: where each begins, and the end of all.

    -> start, number of suffixes, text number, anchor hash and two hashes of the run's text, of every run.
    """
    window = length - gram + 1
    low = np.uint64((1 << 22) - 1)
    sums = prefix_sums(x, 0)
    n = len(x) - gram + 1
    grams = _mixed((sums[gram:] - sums[:n]) * _tables()[1][:n])
    # the rightmost of equal grams wins: places count down in the low bits
    m = (grams & ~low) | (low - np.arange(n, dtype=np.uint64))
    have = 1
    while have < window:
        step = min(have, window - have)
        m = np.minimum(m[:-step], m[step:])
        have += step
    at = (low - (m & low)).astype(np.int64)
    text = np.repeat(np.arange(len(cuts) - 1), np.diff(cuts))[: len(at)]
    inside = np.arange(len(at)) + length <= cuts[1:][text]
    key = np.where(inside, at, -1)
    first = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (text[1:] != text[:-1])]))
    count = np.diff(np.concatenate([first, [len(key)]]))
    first, count = first[inside[first]], count[inside[first]]
    end = first + count + length - 1
    f1, f2 = span_hashes(sums, first, end, 0), span_hashes(prefix_sums(x, 1), first, end, 1)
    return first, count, text[first], grams[at[first]], f1, f2


def _pieces(batch: pa.RecordBatch, length: int) -> Iterator[tuple]:
    """Texts of a batch in pieces of about PIECE bytes: bytes, cuts, row of each text and its offset. Longer texts are
    cut in overlapping parts, so that every suffix is in one of them."""
    parts: list[bytes] = []
    rows: list[int] = []
    offsets: list[int] = []
    size = 0
    for row, t in enumerate(utf8(batch.column(2))):
        if t is None or len(t) < length:
            continue
        for at in range(0, len(t) - length + 1, PIECE):
            part = t[at : at + PIECE + length - 1]
            parts.append(part)
            rows.append(row)
            offsets.append(at)
            size += len(part)
            if size >= PIECE:
                yield np.frombuffer(b"".join(parts), np.uint8), np.cumsum([0, *map(len, parts)]), np.array(rows), np.array(offsets)
                parts, rows, offsets, size = [], [], [], 0
    if parts:
        yield np.frombuffer(b"".join(parts), np.uint8), np.cumsum([0, *map(len, parts)]), np.array(rows), np.array(offsets)


def all_runs(rows: DataFrame, length: int, gram: int, spans: bool) -> DataFrame:
    """Runs of rows(sb_doc, sb_row, text): sb_anchor and, if spans, where they are and the hashes of their text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x, cuts, row, offset in _pieces(batch, length):
                start, count, text, anchor, f1, f2 = suffix_runs(x, cuts, length, gram)
                anchors = pa.array(anchor.view(np.int64))
                if not spans:
                    yield pa.RecordBatch.from_arrays([anchors], ["sb_anchor"])
                    continue
                at, place = pa.array(row[text]), pa.array(start - cuts[text] + offset[text])
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).take(at), batch.column(1).take(at), place, pa.array(count.astype(np.int32)), anchors, pa.array(f1.view(np.int64)), pa.array(f2.view(np.int64))],
                    ["sb_doc", "sb_row", "sb_start", "sb_count", "sb_anchor", "sb_f1", "sb_f2"],
                )

    id_type = rows.schema["sb_doc"].dataType.simpleString()
    return rows.select("sb_doc", "sb_row", "text").mapInArrow(run, f"sb_doc {id_type}, sb_row long, sb_start long, sb_count int, sb_anchor long, sb_f1 long, sb_f2 long" if spans else "sb_anchor long")


# --- one bucket -------------------------------------------------------------------------------------------------------

COVER = 16
ROOT = 4
#: Every number below COVER is a difference of two of these, modulo COVER: multiples of the root, and less than it.
IN_COVER = np.array([x < ROOT or x % ROOT == 0 for x in range(COVER)])
#: SHIFT[i, j]: the least number that takes both i and j into the cover.
SHIFT = np.array([[next(d for d in range(COVER) if IN_COVER[(i + d) % COVER] and IN_COVER[(j + d) % COVER]) for j in range(COVER)] for i in range(COVER)])


def _dense(*keys: np.ndarray) -> np.ndarray:
    """Rank of each row of keys in their sorted order, equal rows alike."""
    order = np.lexsort(keys[::-1])
    new = np.zeros(len(order), np.int64)
    for k in keys:
        new[1:] |= k[order[1:]] != k[order[:-1]]
    ranks = np.empty(len(order), np.int64)
    ranks[order] = np.cumsum(new)
    return ranks


def cover_ranks(x: np.ndarray, eights: np.ndarray, depth: int) -> np.ndarray:
    """Ranks, to depth bytes (COVER times a power of two), of the suffixes at places in the cover; elsewhere -1."""
    places = np.flatnonzero(np.resize(IN_COVER, len(x)))
    ranks = np.full(len(x) + depth, -1, np.int64)
    ranks[places] = _dense(eights[places], eights[places + 8])
    have = COVER
    while have < depth:
        ranks[places] = _dense(ranks[places], ranks[places + have])
        have *= 2
    return ranks


def repeated_in_bucket(x: np.ndarray, starts: np.ndarray, length: int) -> np.ndarray:
    """Which of the suffixes at starts have, to length bytes, an equal among the others.

    They are sorted by their first COVER bytes and their last ones before length; ties are resolved by ranks of the
    cover's suffixes, computed once: two tied suffixes have a place in the cover at the same distance, below COVER,
    and the ranks from there on cover what the sort did not read.
    """
    depth = COVER
    while 2 * depth <= length - COVER + 1:
        depth *= 2
    reach = (length - (COVER - 1) - depth) // COVER * COVER  # a second place, as far on as the length lets it
    tail = length - reach - depth  # bytes that neither rank covers, where the shift is 0
    if reach > depth:
        raise ValueError("length is too far from COVER times a power of two")
    padded = np.concatenate([x, np.zeros(length + 2 * depth + 16, np.uint8)]).astype(np.uint64)
    eights = padded[: len(x) + length + depth].copy()
    for i in range(1, 8):
        eights = (eights << np.uint64(8)) | padded[i : i + len(eights)]
    ranks = cover_ranks(x, eights, depth)
    keys = [eights[starts], eights[starts + 8], *(eights[starts + length - 8 * i] for i in range(1, (tail + 7) // 8 + 1))]
    tie = _dense(*keys)
    order = np.argsort(tie, kind="stable")
    order = order[np.isin(tie[order], np.flatnonzero(np.bincount(tie) > 1))]
    repeated = np.zeros(len(starts), bool)
    while len(order):
        group = tie[order]
        head = np.concatenate([[True], group[1:] != group[:-1]])
        leader = order[np.flatnonzero(head)[np.cumsum(head) - 1]]
        i, j = starts[leader], starts[order]
        shift = SHIFT[i % COVER, j % COVER]
        same = (ranks[i + shift] == ranks[j + shift]) & (ranks[i + shift + reach] == ranks[j + shift + reach])
        found = same & ~head
        repeated[order[found]] = True
        repeated[leader[found]] = True
        order = order[~same]
    return repeated


def _sort_buckets(length: int):
    names = ["sb_doc", "sb_row", "sb_start", "sb_count"]

    def solve(rows: list[tuple], schema: list) -> pa.RecordBatch:
        texts = [r[5] for r in rows]
        cuts = np.cumsum([0, *map(len, texts)])
        counts = np.array([len(t) - length + 1 for t in texts])
        starts = np.concatenate([np.arange(c) + a for a, c in zip(cuts, counts)])
        hit = repeated_in_bucket(np.frombuffer(b"".join(texts), np.uint8), starts, length)
        owner = np.repeat(np.arange(len(rows)), counts)
        edge = np.flatnonzero(np.concatenate([[True], (hit[1:] != hit[:-1]) | (owner[1:] != owner[:-1])]))
        size = np.diff(np.concatenate([edge, [len(hit)]]))
        edge, size = edge[hit[edge]], size[hit[edge]]
        own = owner[edge]
        at = starts[edge] - cuts[own]
        picked = [rows[o] for o in own]
        cols = [[r[0] for r in picked], [r[1] for r in picked], [r[2] + int(a) for r, a in zip(picked, at)], size.astype(np.int32)]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, schema)], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size, last, schema = 0, None, None
        for batch in batches:
            schema = [batch.schema.field(i).type for i in range(3)] + [pa.int32()]
            for r in zip(*(batch.column(i).to_pylist() for i in range(6))):
                if size >= BUCKET and r[4] != last:
                    yield solve(held, schema)
                    held, size = [], 0
                held.append(r)
                size += len(r[5])
                last = r[4]
        if held:
            yield solve(held, schema)

    return run


def _window_hashes(length: int):
    """Of each run's text, the two hashes of every suffix to length bytes."""
    names = ["sb_doc", "sb_row", "sb_start", "sb_f1", "sb_f2"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for doc, row, start, text in zip(*(batch.column(i).to_pylist() for i in (0, 1, 2, 5))):
                x = np.frombuffer(text, np.uint8)
                at = np.arange(len(x) - length + 1)
                f = [pa.array(span_hashes(prefix_sums(x, k), at, at + length, k).view(np.int64)) for k in (0, 1)]
                same = [pa.array([v] * len(at), batch.schema.field(i).type) for i, v in ((0, doc), (1, row))]
                yield pa.RecordBatch.from_arrays([*same, pa.array(at + start), *f], names)

    return run


def met_with(rows: DataFrame, other: DataFrame, how: str) -> DataFrame:
    """rows with what other has of the same sb_doc, null or not, and sb_row."""
    o = other.withColumnsRenamed({"sb_doc": "sb_doc2", "sb_row": "sb_row2"})
    return rows.join(o, F.col("sb_doc").eqNullSafe(F.col("sb_doc2")) & (F.col("sb_row") == F.col("sb_row2")), how).drop("sb_doc2", "sb_row2")


def repeated_suffixes(rows: DataFrame, length: int = 200, gram: int = GRAM, largest: int = LARGEST) -> DataFrame:
    """rows(sb_doc, sb_row, text) -> sb_doc, sb_row, sb_start, sb_count: the suffixes that repeat to length bytes.

    1. Count the anchors; runs with an anchor that stands once are dropped (count, then a semi join on the anchor).
    2. Runs of equal text, by 128 bits of hash, are one class. Where a class has two runs, all its suffixes repeat.
    3. Where an anchor has a class of one run and other classes, one run of each class goes, with its text, to the
       anchor's bucket, and the suffixes are sorted there.
    4. A bucket of over `largest` runs is not sorted in one task: its suffixes are dealt out by hash and counted.
    """
    # written first, so that both sides of the join come by an exchange and a frequent anchor's side can be split
    anchors = written(all_runs(rows, length, gram, False).groupBy("sb_anchor").agg(F.count("*").alias("sb_n")).filter("sb_n > 1").select("sb_anchor"), "anchors")
    runs = written(all_runs(rows, length, gram, True).join(anchors, "sb_anchor", "left_semi"), "runs")
    key = ["sb_anchor", "sb_f1", "sb_f2"]
    place = ["sb_doc", "sb_row", "sb_start", "sb_count"]
    classes = runs.groupBy(*key).agg(F.count("*").alias("sb_n"), F.min(F.struct(*place)).alias("sb_one"))
    copied = runs.join(written(classes.filter("sb_n > 1").select(*key), "copied-classes"), key, "left_semi").select(*place)
    mixed = written(classes.groupBy("sb_anchor").agg(F.count("*").alias("sb_classes"), F.min("sb_n").alias("sb_least")).filter("sb_classes > 1 AND sb_least = 1"), "mixed-anchors")
    one = classes.join(mixed.select("sb_anchor", "sb_classes"), "sb_anchor").select("sb_one.*", "sb_anchor", "sb_classes")
    wanted = one.groupBy("sb_doc", "sb_row").agg(F.collect_list(F.struct("sb_start", "sb_count", "sb_anchor", "sb_classes")).alias("sb_runs"))
    texts = met_with(rows, wanted, "inner")
    texts = texts.select("sb_doc", "sb_row", F.col("text").cast("binary").alias("b"), F.explode("sb_runs").alias("r"))
    texts = texts.select("sb_doc", "sb_row", "r.sb_start", "r.sb_count", "r.sb_anchor", F.expr(f"substring(b, CAST(r.sb_start AS INT) + 1, r.sb_count + {length - 1})").alias("sb_text"), "r.sb_classes")
    columns = texts.columns[:6]
    small = texts.filter(F.col("sb_classes") <= largest).select(columns).repartition("sb_anchor").sortWithinPartitions("sb_anchor")
    id_type = rows.schema["sb_doc"].dataType.simpleString()
    sorted_out = small.mapInArrow(_sort_buckets(length), f"sb_doc {id_type}, sb_row long, sb_start long, sb_count int")
    single = texts.filter(F.col("sb_classes") > largest).select(columns).mapInArrow(_window_hashes(length), f"sb_doc {id_type}, sb_row long, sb_start long, sb_f1 long, sb_f2 long")
    twice = single.groupBy("sb_f1", "sb_f2").agg(F.count("*").alias("sb_n")).filter("sb_n > 1").select("sb_f1", "sb_f2")
    dealt = single.join(twice, ["sb_f1", "sb_f2"], "left_semi").select("sb_doc", "sb_row", "sb_start", F.lit(1).alias("sb_count"))
    return copied.unionByName(sorted_out).unionByName(dealt)


def remove_repeats(docs: DataFrame, length: int = 200, gram: int = GRAM, largest: int = LARGEST) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and kept (the bytes that stay) of each row of docs(doc_id, text).

    Every byte covered by a string of length bytes that starts anywhere else too is removed, from all its places.
    Null text counts as empty. Equal rows are documents of their own, so they remove each other. A null doc_id is an id
    like any other, and ids may be of any type. Extra columns are ignored. Empty table: no rows. A long text is read in
    pieces of PIECE bytes.
    """
    # a row is known by its id, of any type and null too, and a hash of its text; equal rows have equal results
    rows = docs.select(F.col("doc_id").alias("sb_doc"), F.xxhash64("text").alias("sb_row"), "text")
    found = repeated_suffixes(rows, length, gram, largest).groupBy("sb_doc", "sb_row").agg(F.collect_list(F.struct("sb_start", "sb_count")).alias("sb_found"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for text, hits in zip(utf8(batch.column(1)), batch.column(2)):
                text = text or b""
                n_spans, kept = 0, [text]
                if hits.is_valid and len(hits):
                    start, count = (hits.values.field(i).to_numpy().astype(np.int64) for i in (0, 1))
                    order = np.argsort(start)
                    start, end = start[order], np.maximum.accumulate((start + count + length - 1)[order])
                    new = np.concatenate([[True], start[1:] > end[:-1]])
                    a, b = start[new], end[np.concatenate([np.flatnonzero(new)[1:] - 1, [len(end) - 1]])]
                    n_spans, kept = len(a), [text[x:y] for x, y in zip([0, *b], [*a, len(text)])]
                rest = b"".join(kept)
                out.append((len(text), len(text) - len(rest), n_spans, hashlib.sha256(rest).hexdigest(), rest))
            cols = zip(*out) if out else [[]] * 5
            kinds = [pa.int64()] * 3 + [pa.string(), pa.binary()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds))], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    # the texts are dealt out as in repeated_suffixes, so that they are once for both joins
    joined = met_with(rows, found, "left").select(F.col("sb_doc").alias("doc_id"), "text", "sb_found")
    id_type = docs.schema["doc_id"].dataType.simpleString()
    return joined.mapInArrow(run, f"doc_id {id_type}, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
