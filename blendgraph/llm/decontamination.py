"""Benchmark decontamination by one Aho-Corasick automaton over normalised items."""

from __future__ import annotations

import hashlib
import math
import re
import uuid

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORDS, per_batch, utf8, written

WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
#: Most MB of item text that one automaton takes. More items make more automata, read one after another.
MAX_ITEM_MB = 16.0
_BUILT: dict[str, list] = {}


def normal_words(text: bytes) -> bytes:
    """The words, a space before and after each."""
    words = text.translate(WORDS).split(b" ")
    joined = b" ".join(w for w in words if w)
    return b" " + joined + b" " if joined else b""


def item_windows(items: list[tuple], width: int) -> dict[bytes, list[str]]:
    """Pattern (words between spaces) -> the ids of the items that hold it."""
    found: dict[bytes, set[str]] = {}
    for item_id, text in items:
        words = normal_words(text or b"").split()
        for i in range(max(1, len(words) - width + 1) if words else 0):
            found.setdefault(b" " + b" ".join(words[i : i + width]) + b" ", set()).add(str(item_id))
    return {k: sorted(v) for k, v in found.items()}


class Scanner:
    """One automaton, built once in each worker."""

    def __init__(self, items: list[tuple], width: int):
        self.automaton = ahocorasick.Automaton()
        for pattern, ids in item_windows(items, width).items():
            self.automaton.add_word(pattern.decode("latin-1"), (pattern.count(b" ") - 1, ids))
        self.empty = not len(self.automaton)
        if not self.empty:
            self.automaton.make_automaton()

    def hits(self, normal: bytes) -> list[tuple[int, int, list[str]]]:
        """Each occurrence as first word, word after the last, item ids. A match ends on the space after its last word,
        so the words before it are the spaces up to there, counted along the text once."""
        if self.empty or not normal:
            return []
        out, word, read = [], -1, 0
        for end, (n, ids) in self.automaton.iter(normal.decode("latin-1")):
            word += normal.count(b" ", read, end + 1)
            read = end + 1
            out.append((word - n, word, ids))
        return out


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def _scanners(token: str, blocks: list[list[tuple]], width: int) -> list[Scanner]:
    if token not in _BUILT:
        _BUILT.clear()
        _BUILT[token] = [Scanner(block, width) for block in blocks]
    return _BUILT[token]


def _item_groups(items: DataFrame, max_item_mb: float) -> list[DataFrame]:
    """The items in groups of about 64 automata: one group, unless there are more items than a worker should hold."""
    known = items.filter("item_id IS NOT NULL").select("item_id", "text").distinct()
    size = (known.selectExpr("sum(octet_length(text)) AS n").first().n or 0) / 1e6
    n = max(1, math.ceil(size / (64 * max_item_mb)))
    return [known] if n == 1 else [known.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == g) for g in range(n)]


def _sent_items(items: DataFrame, width: int, max_item_mb: float):
    """A function that returns the worker's automata of one group of items."""
    rows = sorted(((r[0], (r[1] or "").encode()) for r in items.collect()), key=str)
    blocks: list[list[tuple]] = [[]]
    room = max_item_mb * 1e6
    for row in rows:
        if (room := room - len(row[1])) < 0 and blocks[-1]:
            blocks.append([])
            room = max_item_mb * 1e6 - len(row[1])
        blocks[-1].append(row)
    sent, token = items.sparkSession.sparkContext.broadcast(blocks), uuid.uuid4().hex
    return lambda: _scanners(token, sent.value, width)


def _all_hits(docs: DataFrame, groups: list[DataFrame], width: int, max_item_mb: float) -> DataFrame:
    """docs(doc_id, text) with hits: spans of words and item ids of all groups. Each group is one pass over the texts; its
    hits are joined by hashes of a row's id and text, so the texts move once, at the end."""
    keyed = docs.select("doc_id", "text", F.xxhash64(F.col("doc_id").isNull(), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).alias("dc_doc"), F.xxhash64("text").alias("dc_row"))
    found = None
    for group in groups:
        scanners = _sent_items(group, width, max_item_mb)

        def run(batch: pa.RecordBatch, scanners=scanners) -> pa.RecordBatch:
            hits = [[h for s in scanners() for h in s.hits(normal_words(t or b""))] for t in utf8(batch.column(2))]
            keep = [i for i, h in enumerate(hits) if h]
            spans = pa.array([[list(x) for x in merged([h[:2] for h in hits[i]])] for i in keep], pa.list_(pa.list_(pa.int64())))
            ids = pa.array([sorted({x for h in hits[i] for x in h[2]}) for i in keep], pa.list_(pa.string()))
            at = pa.array(keep, pa.int64())
            return pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at), spans, ids], ["dc_doc", "dc_row", "spans", "ids"])

        part = written(keyed.select("dc_doc", "dc_row", "text").mapInArrow(per_batch(run), "dc_doc long, dc_row long, spans array<array<long>>, ids array<string>"), "hits")
        found = part if found is None else found.unionByName(part)
    each = found.groupBy("dc_doc", "dc_row").agg(F.flatten(F.collect_list("spans")).alias("spans"), F.array_distinct(F.flatten(F.collect_list("ids"))).alias("ids"))
    return keyed.join(each, ["dc_doc", "dc_row"], "left").select("doc_id", "text", "spans", "ids")


def find_contamination(docs: DataFrame, items: DataFrame, width: int = 10, max_item_mb: float = MAX_ITEM_MB) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated and the hit spans of the original text in characters.

    A window is width consecutive words of an item, or all words of a shorter one. The documents are read once and
    not shuffled. Test sets are small by nature: the items go to the executors, in automata of max_item_mb at most. Of
    more than 64 of those, each 64 are a pass of their own, and the hits are put together. Matches' offsets lead back to
    the text by the words they cover.

    Null or empty text: no words, not contaminated. Null or empty item: no window. Repeated items: one of them. An item
    without an id is none, as it could not be named. Empty tables: no rows, or no hits. Extra columns are ignored; repeated
    documents are judged each. A long text is held once with its words.
    """
    groups = _item_groups(items, max_item_mb)
    several = len(groups) > 1
    scanners = None if several else _sent_items(groups[0], width, max_item_mb)
    none = hashlib.sha256(b"").hexdigest()

    def scan(text: bytes, spans: list | None, ids: list | None) -> tuple:
        normal = normal_words(text)
        n_words = max(0, normal.count(b" ") - 1)
        if scanners is not None:
            hits = [h for s in scanners() for h in s.hits(normal)]
            spans, ids = [h[:2] for h in hits], {i for h in hits for i in h[2]}
        if not spans:
            return n_words, 0, 0, none, False, []
        spans, ids = merged([tuple(x) for x in spans]), sorted(ids)
        places = np.array([m.span() for m in WORD.finditer(text.translate(WORDS))])
        first = np.cumsum(np.frombuffer(text, np.uint8) & 0xC0 != 0x80)  # characters up to each byte
        chars = [[int(first[places[a, 0]]) - 1, int(first[places[b - 1, 1] - 1])] for a, b in spans]
        return n_words, sum(b - a for a, b in spans), len(ids), hashlib.sha256(",".join(ids).encode()).hexdigest(), True, chars

    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_(), pa.list_(pa.list_(pa.int64()))]
    names = ["n_words", "n_hit", "n_items", "items_sha256", "contaminated", "hit_spans"]

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = utf8(batch.column(1))
        known = zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()) if several else ((None, None) for _ in texts)
        rows = [scan(t or b"", *k) for t, k in zip(texts, known)]
        cols = zip(*rows) if rows else [[]] * len(names)
        return pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds))], ["doc_id", *names])

    d = _all_hits(docs, groups, width, max_item_mb) if several else docs.select("doc_id", "text")
    return d.mapInArrow(per_batch(run), f"doc_id {d.schema['doc_id'].dataType.simpleString()}, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, hit_spans array<array<long>>")


def drop_contaminated(docs: DataFrame, items: DataFrame, width: int = 10, max_item_mb: float = MAX_ITEM_MB) -> DataFrame:
    """docs, all columns, without the contaminated ones, judged as by find_contamination. No shuffle: the text is judged
    where it is read. Null and empty texts stay, whatever their other columns hold; an empty table gives an empty one."""
    at, groups = docs.columns.index("text"), _item_groups(items, max_item_mb)
    for number, group in enumerate(groups):
        scanners = _sent_items(group, width, max_item_mb)

        def run(batch: pa.RecordBatch, scanners=scanners) -> pa.RecordBatch:
            normal = map(normal_words, (t or b"" for t in utf8(batch.column(at))))
            return batch.filter(pa.array([not any(s.hits(n) for s in scanners()) for n in normal], pa.bool_()))

        docs = docs.mapInArrow(per_batch(run), docs.schema)
        # a worker holds the automata of one group at a time
        docs = written(docs, "clean") if number < len(groups) - 1 else docs
    return docs
