"""SimHash near-duplicates: fingerprints, pigeonhole blocks, Hamming check, components.

`near_duplicates` links fingerprints of one kind. `near_copies` finds texts whose five-word shingles are similar: blocks
come from fingerprints of the words, which an edit moves by a few bits, and the Hamming check adds a longer fingerprint
of the shingles, whose distance stands for their similarity.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, per_batch, utf8, written
from .components import connected_components

SEED = 42
PIECE = 1 << 15
#: Blocks of up to so many values are compared in full, larger ones by a spanning forest.
SMALL = 32
#: Longs of a fingerprint of shingles.
LONGS = 4


def shingle_hashes(words: list[bytes], width: int) -> Iterator[np.ndarray]:
    """XXH64 of the shingles, repeats included, in arrays of PIECE at most; fewer words than width are one shingle."""
    normal = b" ".join(words)
    n = max(1, len(words) - width + 1)
    gaps = np.flatnonzero(np.frombuffer(normal, np.uint8) == 32)
    starts = np.concatenate([[0], gaps + 1])[:n].tolist()
    ends = np.concatenate([gaps, [len(normal)]])[-n:].tolist()
    for at in range(0, n, PIECE):
        yield np.array([xxhash.xxh64_intdigest(normal[a:b], SEED) for a, b in zip(starts[at : at + PIECE], ends[at : at + PIECE])], "<u8")


def bits_of(h: np.ndarray) -> np.ndarray:
    """One row a hash, one column a bit, the lowest first."""
    return np.unpackbits(h.view(np.uint8).reshape(len(h), -1), axis=1, bitorder="little")


def packed(counts: np.ndarray, total: int) -> list[int]:
    """The bits that hold over half of total, as signed longs."""
    return np.packbits(2 * counts > total, bitorder="little").view("<i8").tolist()


def fingerprint(text: bytes, width: int = 4) -> int:
    """64 bits, each the majority among the XXH64 of the text's shingles; no words: 0."""
    words = text.translate(LOWER).split()
    if not words:
        return 0
    counts, n = np.zeros(64, np.int64), 0
    for h in shingle_hashes(words, width):
        counts += bits_of(h).sum(axis=0, dtype=np.int64)
        n += len(h)
    return packed(counts, n)[0]


def widened(h: np.ndarray) -> np.ndarray:
    """LONGS hashes for each, by a mixing of 64 bits."""
    x = h[:, None] + np.arange(1, LONGS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return x ^ (x >> np.uint64(31))


def copy_fingerprints(text: bytes, width: int = 5) -> list[int]:
    """Of the words, 64 bits: each word weighs 16 · (1 + ln count), rounded. Of the shingles, 64 · LONGS bits."""
    words = text.translate(LOWER).split()
    if not words:
        return [0] * (1 + LONGS)
    counted = Counter(words)
    weights = np.array([round(16 * (1 + math.log(n))) for n in counted.values()], np.int64)
    hashes = np.array([xxhash.xxh64_intdigest(w, SEED) for w in counted], "<u8")
    out = packed(weights @ bits_of(hashes).astype(np.int64), int(weights.sum()))
    counts, n = np.zeros(64 * LONGS, np.int64), 0
    for h in shingle_hashes(words, width):
        counts += bits_of(widened(h)).sum(axis=0, dtype=np.int64)
        n += len(h)
    return out + packed(counts, n)


def fingerprints(docs: DataFrame, width: int = 4) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long) of each row. Null text counts as empty."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array([fingerprint(t or b"", width) for t in utf8(batch.column(1))], pa.int64())], ["doc_id", "fp"])

    d = docs.select("doc_id", "text")
    return d.mapInArrow(per_batch(run), f"doc_id {d.schema['doc_id'].dataType.simpleString()}, fp long")


def piece_masks(max_bits: int, r: int) -> list[int]:
    """Masks such that two values that differ in max_bits bits or fewer agree under one of them.

    The 64 bits are cut into max_bits + r pieces. max_bits differing bits touch max_bits pieces at most, so r others
    agree: a mask for each choice of r pieces. Whatever r is, the pairs found are the same; a larger one makes more and
    smaller blocks.
    """
    cuts = [round(64 * i / (max_bits + r)) for i in range(max_bits + r + 1)]
    pieces = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in zip(cuts, cuts[1:])]
    return [sum(c) for c in combinations(pieces, r)]


def block_masks(max_bits: int, n: int) -> list[int]:
    """Masks of as many pieces, up to 4, as it takes for blocks of n evenly spread values to hold 4 on average."""
    for r in range(1, 65 - max_bits):
        masks = piece_masks(max_bits, r)
        if min(m.bit_count() for m in masks) + 2 >= n.bit_length() or r >= 4:
            return masks
    return masks


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def distance(a: np.ndarray, b) -> np.ndarray:
    """Differing bits. As unsigned: bitwise_count would take a negative number's absolute value."""
    return np.bitwise_count((a ^ b).view(np.uint64))


#: Which columns of a row make one fingerprint, and in how many bits linked ones differ at most.
Limits = tuple[tuple[slice, int], ...]


def near(a: np.ndarray, b: np.ndarray, limits: Limits) -> np.ndarray:
    """Which rows of a are within all limits of b (rows as many as a's, or one)."""
    first, most = limits[0]
    ok = np.atleast_1d(distance(a[:, first], b[..., first]).sum(axis=-1) <= most)
    for columns, most in limits[1:]:
        at = np.flatnonzero(ok)
        other = b[at] if b.ndim > 1 else b
        ok[at] = distance(a[at][:, columns], other[..., columns]).sum(axis=-1) <= most
    return ok


def forest(group: np.ndarray, limits: Limits) -> list[tuple[int, int]]:
    """Edges that span the components of one block's rows (node, fingerprints): each is compared with those not yet reached."""
    edges, left = [], group
    while len(left) > 1:
        front, left = [left[0]], left[1:]
        while front and len(left):
            x = front.pop()
            ok = near(left, x, limits)
            if ok.any():
                edges += [(int(x[0]), int(y)) for y in left[ok, 0]]
                front += list(left[ok])
                left = left[~ok]
    return edges


def _block_edges(n_keys: int, limits: Limits):
    """Edges of rows (keys of the block, node, fingerprints), which come sorted by the keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest = None
        for batch in batches:
            rows = np.column_stack([c.to_numpy(zero_copy_only=False) for c in batch.columns])
            rest = yield from blocks(rows if rest is None else np.concatenate([rest, rows]), False)
        if rest is not None:
            yield from blocks(rest, True)

    def blocks(rows: np.ndarray, ended: bool):
        if not len(rows):
            return rows
        keys, values = rows[:, :n_keys], np.ascontiguousarray(rows[:, n_keys:])
        cut = np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1
        bounds = np.concatenate([[0], cut, [len(rows)] if ended else []]).astype(int)
        sizes = np.diff(bounds)
        edges = [(values[:0, 0], values[:0, 0])]
        # small blocks all at once: each value with those up to SMALL - 1 places further on in its block
        end = np.repeat(bounds[1:], sizes)
        at = np.flatnonzero(np.repeat((sizes > 1) & (sizes <= SMALL), sizes))
        for d in range(1, SMALL):
            at = at[at + d < end[at]]
            if not len(at):
                break
            met = at[near(values[at], values[at + d], limits)]
            edges.append((values[met, 0], values[met + d, 0]))
        for a, b in zip(bounds[:-1][sizes > SMALL], bounds[1:][sizes > SMALL]):
            if found := forest(values[a:b], limits):
                edges.append(tuple(np.array(found, np.int64).T))
        a, b = (np.concatenate(z) for z in zip(*edges))
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])
        return rows[bounds[-1] :]

    return run


def _blocked(values: DataFrame, masks: list[int]) -> DataFrame:
    """values(fp, ...) once for each mask, with t (the mask) and k (the masked value)."""
    keys = F.array(*[F.struct(F.lit(i).cast("long").alias("t"), F.col("fp").bitwiseAND(F.lit(signed(m))).alias("k")) for i, m in enumerate(masks)])
    return values.select("*", F.explode(keys).alias("x")).select("x.t", "x.k", *values.columns)


def hamming_edges(values: DataFrame, max_bits: int = 4, largest_block: int = 20_000) -> DataFrame:
    """values(fp), distinct -> edges (a, b) whose components are those of all pairs at max_bits or fewer differing bits.

    Values meet in blocks (mask, masked value). A block of largest_block values or fewer goes to one task, which checks
    the Hamming distance and returns a spanning forest, never all pairs. The values of larger blocks are linked by
    midpoints: two values within max_bits share a value within ceil(max_bits / 2) of both, and values around one
    midpoint, at max_bits // 2 and ceil(max_bits / 2), are within max_bits of each other. That is linear in the block.
    """
    rows = _blocked(values.select("fp"), block_masks(max_bits, values.count()))
    # written first, so that both sides of the join come by an exchange and a large block's side can be split
    sizes = written(rows.groupBy("t", "k").agg(F.count("*").alias("n")).filter("n > 1"), "block-sizes")
    met = written(rows.join(sizes, ["t", "k"]), "blocks")
    small = met.filter(F.col("n") <= largest_block).select("t", "k", "fp").repartition("t", "k").sortWithinPartitions("t", "k", "fp")
    edges = small.mapInArrow(_block_edges(2, ((slice(0, 1), max_bits),)), "a long, b long")
    large = met.filter(F.col("n") > largest_block).select("fp").distinct()
    if not large.isEmpty():
        edges = edges.unionByName(midpoint_edges(large, max_bits))
    return edges


def midpoint_edges(values: DataFrame, max_bits: int) -> DataFrame:
    far, near = (max_bits + 1) // 2, max_bits // 2
    flips = [(d, signed(sum(1 << b for b in bits))) for d in range(far + 1) for bits in combinations(range(64), d)]
    at = values.select("fp", F.explode(F.lit([m for _, m in flips])).alias("m")).selectExpr("fp", "fp ^ m AS mid", "bit_count(m) AS d")
    # with an odd max_bits the pair is one inner and one outer value of a midpoint: outer ones link to its least inner one
    inner = at.filter(F.col("d") <= near).groupBy("mid").agg(F.min("fp").alias("a"))
    return at.join(inner, "mid").filter("fp <> a").selectExpr("a", "fp AS b").distinct()


def near_duplicates(docs: DataFrame, width: int = 4, max_bits: int = 4, largest_block: int = 20_000) -> DataFrame:
    """doc_id, fp, component_id: the smallest doc_id among the documents reached by links of max_bits or fewer bits.

    Documents of one fingerprint count as one value before anything is joined, so exact copies cost one row. Null or
    empty texts have fingerprint 0 and link like any other. A null doc_id gets a component but is never its smallest.
    Repeated rows get the same result; extra columns are ignored; an empty table gives no rows.
    """
    each = written(fingerprints(docs, width), "fingerprints")
    values = written(each.groupBy("fp").agg(F.min("doc_id").alias("least")), "values")
    roots = connected_components(hamming_edges(values.select("fp"), max_bits, largest_block))
    rooted = values.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    rooted = written(rooted.select("fp", "least", "root"), "rooted")
    least = written(rooted.groupBy("root").agg(F.min("least").alias("component_id")), "least")
    # AQE splits the documents of a large group over tasks: each value has one row on the other side
    return each.join(rooted.join(least, "root").select("fp", "component_id"), "fp", "left").select("doc_id", "fp", "component_id")


def similar_edges(values: DataFrame, max_bits: int, check_bits: int, largest_block: int = 20_000, pieces: int = 2) -> DataFrame:
    """values(node, fp, g0 ...) -> edges (a, b) whose components are those of all pairs within max_bits of fp and
    check_bits of the g's.

    Blocks by masks of fp, as in hamming_edges, of `pieces` pieces: with 2 and 7 bits, each value is in 36 blocks of 14
    bits or more (3: 120 of 18, for tables of billions of documents). A block of over largest_block rows is dealt into parts of half that
    size, and each two parts meet in a task, which returns a spanning forest: no task has more than largest_block rows.
    """
    rows = _blocked(values, piece_masks(max_bits, pieces))
    large = written(rows.groupBy("t", "k").agg(F.count("*").alias("n")).filter(F.col("n") > largest_block), "large-blocks")
    limits = ((slice(1, 2), max_bits), (slice(2, 2 + LONGS), check_bits))
    some = not large.isEmpty()
    small = (rows.join(large, ["t", "k"], "left_anti") if some else rows).repartition("t", "k").sortWithinPartitions("t", "k", "node")
    edges = small.mapInArrow(_block_edges(2, limits), "a long, b long")
    if some:
        parts = F.ceil(F.col("n") * 2 / largest_block).cast("long")
        d = rows.join(large, ["t", "k"]).withColumn("parts", parts).withColumn("p", F.pmod(F.xxhash64("node"), F.col("parts")))
        d = d.withColumn("q", F.explode(F.expr("sequence(0L, parts - 1)")))
        keys = ["t", "k", "p", "q"]
        d = d.select("t", "k", F.least("p", "q").alias("p"), F.greatest("p", "q").alias("q"), *values.columns)
        edges = edges.unionByName(d.repartition(*keys).sortWithinPartitions(*keys, "node").mapInArrow(_block_edges(4, limits), "a long, b long"))
    return edges


def near_copies(docs: DataFrame, width: int = 5, max_bits: int = 7, check_bits: int = 46, largest_block: int = 20_000, pieces: int = 2) -> DataFrame:
    """doc_id, component_id: the smallest doc_id among the documents reached by links between similar texts.

    Two texts link if their words' fingerprints differ in max_bits of 64 or fewer, and their shingles' in check_bits of
    256 or fewer. Texts whose shingles have a Jaccard similarity of 0.8 differ on average in 39 of these 256 bits (an
    angle with the cosine 2 · 0.8 / 1.8), with a standard deviation below 6. Texts of equal fingerprints are one value
    before anything is joined. Nulls, empty texts, repeats and extra columns are handled as by near_duplicates.
    """
    names = ["fp", *(f"g{i}" for i in range(LONGS))]

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = [copy_fingerprints(t or b"", width) for t in utf8(batch.column(1))]
        return pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, pa.int64()) for c in (zip(*rows) if rows else [[]] * len(names)))], ["doc_id", *names])

    d = docs.select("doc_id", "text")
    made = d.mapInArrow(per_batch(run), f"doc_id {d.schema['doc_id'].dataType.simpleString()}, " + ", ".join(f"{n} long" for n in names))
    each = written(made.withColumn("node", F.xxhash64(*names)), "copy-fingerprints")
    values = written(each.groupBy("node", *names).agg(F.min("doc_id").alias("least")), "values")
    roots = connected_components(similar_edges(values.select("node", *names), max_bits, check_bits, largest_block, pieces))
    rooted = values.select("node", "least").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    rooted = written(rooted, "rooted")
    least = written(rooted.groupBy("root").agg(F.min("least").alias("component_id")), "least")
    return each.select("doc_id", "node").join(rooted.join(least, "root").select("node", "component_id"), "node", "left").select("doc_id", "component_id")


def keep_one_each(docs: DataFrame, width: int = 5, max_bits: int = 7, check_bits: int = 46) -> DataFrame:
    """docs, all columns, with the smallest doc_id of each group of near copies. Rows without a doc_id stay; of rows that
    share one, all stay. An empty table gives an empty one."""
    losers = near_copies(docs, width, max_bits, check_bits).filter("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(losers, "doc_id", "left_anti").select(*docs.columns)
