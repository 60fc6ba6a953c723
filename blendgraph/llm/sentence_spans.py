"""Substring dedup by sliding sentence spans."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, utf8, written

# fixed values: end marks, those that need white space behind them and those that do not
WITH_SPACE = (b".", b"!", b"?", "…".encode())
ALONE = tuple(x.encode() for x in "。！？")
SPACE = np.zeros(256, bool)
SPACE[list(b" \t\n\r\x0b\x0c")] = True
_MIX = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F], np.uint64)


def _last_bytes(x: np.ndarray, marks: tuple[bytes, ...]) -> np.ndarray:
    """Where a mark ends."""
    out = np.zeros(len(x), bool)
    for m in marks:
        hit = x[len(m) - 1 :] == m[-1]
        for back in range(1, len(m)):
            hit &= x[len(m) - 1 - back : len(x) - back] == m[-1 - back]
        out[len(m) - 1 :] |= hit
    return out


def pieces(text: bytes) -> list[tuple[int, int]]:
    """Sentences as byte ranges that together are the text. One ends behind an end mark that white space follows, behind a
    full-width mark, and behind a line that has no mark at its end."""
    if not text:
        return []
    x = np.frombuffer(text, np.uint8)
    space, alone, marks = SPACE[x], _last_bytes(x, ALONE), _last_bytes(x, WITH_SPACE)
    after = alone.copy()
    after[:-1] |= marks[:-1] & space[1:]
    after[1:] |= (x[1:] == 10) & ~(space | alone | marks)[:-1]
    after[-1] = False
    cuts = [0, *(np.flatnonzero(after) + 1).tolist(), len(text)]
    return list(zip(cuts, cuts[1:]))


def runs(text: bytes, width: int, min_words: int) -> tuple[list[tuple[int, int]], np.ndarray, np.ndarray]:
    """The pieces that are no white space, the numbers of the runs of width of them, and two hashes of each.

    Sentences are compared without A-Z case and the white space around them. Fewer sentences are one run.
    """
    low = text.translate(LOWER)
    kept, hashes, words = [], [], []
    for a, b in pieces(text):
        if s := low[a:b].strip():
            kept.append((a, b))
            hashes.append(xxhash.xxh3_128_digest(s))
            words.append(len(s.split()))
    if not kept:
        return kept, np.zeros(0, np.int64), np.zeros((0, 2), np.int64)
    h = np.frombuffer(b"".join(hashes), "<u8").reshape(-1, 2)
    n = max(1, len(kept) - width + 1)
    total = np.concatenate([[0], np.cumsum(words)])
    out = np.zeros((n, 2), np.uint64)
    for i in range(min(width, len(kept))):
        out = (out ^ h[i : i + n]) * _MIX
        out ^= out >> np.uint64(31)
    at = np.flatnonzero(total[np.minimum(np.arange(n) + width, len(kept))] - total[:n] >= min_words)
    return kept, at, out[at].view(np.int64)


def _rows(docs: DataFrame) -> DataFrame:
    return docs.filter("doc_id IS NOT NULL").withColumns({"ss_doc": F.col("doc_id"), "ss_row": F.xxhash64("text")})


def all_runs(rows: DataFrame, width: int, min_words: int) -> DataFrame:
    """ss_doc, ss_row, ss_no, ss_h1 and ss_h2 of every run of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            owner, number, hashes = [], [], []
            size = 0
            for i, t in enumerate(utf8(batch.column(2))):
                if t:
                    _, at, h = runs(t, width, min_words)
                    owner.append(np.full(len(at), i))
                    number.append(at)
                    hashes.append(h)
                    size += len(at)
                if size > 100_000 or i == batch.num_rows - 1 and size:
                    o, h = pa.array(np.concatenate(owner)), np.concatenate(hashes)
                    yield pa.RecordBatch.from_arrays(
                        [batch.column(0).take(o), batch.column(1).take(o), pa.array(np.concatenate(number).astype(np.int32)), pa.array(h[:, 0].copy()), pa.array(h[:, 1].copy())],
                        ["ss_doc", "ss_row", "ss_no", "ss_h1", "ss_h2"],
                    )
                    owner, number, hashes, size = [], [], [], 0

    id_type = rows.schema["ss_doc"].dataType.simpleString()
    return rows.select("ss_doc", "ss_row", "text").mapInArrow(run, f"ss_doc {id_type}, ss_row long, ss_no int, ss_h1 long, ss_h2 long")


def repeated_spans(rows: DataFrame, width: int, min_words: int) -> DataFrame:
    """ss_doc, ss_row, ss_nos: the runs that are not the first of their kind. The first is in the smallest doc_id."""
    each = all_runs(rows, width, min_words)
    key = ["ss_h1", "ss_h2"]
    # written first, so that both sides of the join come by an exchange and a frequent run's side can be split
    first = written(each.groupBy(*key).agg(F.count("*").alias("ss_n"), F.min("ss_doc").alias("ss_first")).filter("ss_n > 1").drop("ss_n"), "runs")
    both = written(each.join(first, key), "repeated-runs")
    # the runs of one kind in its first document: no more than the document has sentences
    own = both.filter("ss_doc = ss_first").groupBy("ss_doc", *key).agg(F.sort_array(F.collect_set(F.struct("ss_row", "ss_no"))).alias("x"))
    own = own.select("ss_doc", F.explode(F.expr("slice(x, 2, size(x))")).alias("y")).select("ss_doc", "y.ss_row", "y.ss_no")
    gone = both.filter("ss_doc <> ss_first").select("ss_doc", "ss_row", "ss_no").unionByName(own)
    return gone.groupBy("ss_doc", "ss_row").agg(F.collect_set("ss_no").alias("ss_nos"))


def drop_repeated_spans(docs: DataFrame, width: int = 3, min_words: int = 12) -> DataFrame:
    """docs, all columns, without the sentences covered by a run that stands elsewhere before; adds ss_sentences and ss_removed.

    Every run of width consecutive sentences with min_words words or more is hashed to 128 bits and joined globally. Null
    text stays null, empty text empty, and an empty table gives an empty one. Rows without a doc_id are left as they are. Equal rows are one document. Columns whose names start
    with ss_ are replaced. Of a long text the bounds and hashes of all sentences are held beside it. Texts move once, by
    doc_id, to meet the numbers of their runs.
    """
    docs = docs.drop(*[c for c in docs.columns if c.startswith("ss_")])
    rows = _rows(docs)
    d = rows.join(repeated_spans(rows, width, min_words), ["ss_doc", "ss_row"], "left").select(*docs.columns, "ss_nos")
    d = d.unionByName(docs.filter("doc_id IS NULL").select(*docs.columns, F.lit(None).cast("array<int>").alias("ss_nos")))
    names, at = docs.columns, docs.columns.index("text")

    def clean(text: bytes | None, nos: list[int] | None) -> tuple:
        kept = runs(text or b"", width, 0)[0]
        if not nos:
            return text, len(kept), 0
        gone = {kept[i] for j in nos for i in range(j, min(j + width, len(kept)))}
        return b"".join(text[a:b] for a, b in pieces(text) if (a, b) not in gone), len(kept), len(gone)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            done = [clean(t, n) for t, n in zip(utf8(batch.column(at)), batch.column(batch.num_columns - 1).to_pylist())]
            cols = batch.columns[:-1]
            cols[at] = pa.array([x[0] for x in done], pa.large_binary()).cast(pa.large_string()).cast(batch.schema.field(at).type)
            counts = [pa.array([x[i] for x in done], pa.int64()) for i in (1, 2)]
            yield pa.RecordBatch.from_arrays([*cols, *counts], [*names, "ss_sentences", "ss_removed"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return d.mapInArrow(run, f"{schema}, ss_sentences long, ss_removed long")
