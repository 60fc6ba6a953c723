"""Line dedup by content-defined chunks of lines and, between their boundaries, by runs of lines."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

#: A line ends a chunk if the rolling hash of it and the line before is 0 in this modulus: chunks of four lines on average.
MODULUS = 4


def with_row(docs: DataFrame) -> DataFrame:
    """Rows that have a doc_id, with lc_doc and lc_row (a hash of the text), which tell rows of one doc_id apart."""
    return docs.filter("doc_id IS NOT NULL").withColumns({"lc_doc": F.col("doc_id"), "lc_row": F.xxhash64("text")})


def chunk_columns(docs: DataFrame, modulus: int = MODULUS) -> DataFrame:
    """Add lc_lines, lc_hashes and lc_ends (numbers of the lines that end a chunk) to docs(text).

    Each line has a hash; the rolling hash of two neighbouring line hashes decides whether a chunk ends there, so an
    inserted or deleted line moves no boundary but the next. The last line always ends one.
    """
    d = docs.withColumn("lc_lines", F.split(F.coalesce(F.col("text"), F.lit("")), "\n", -1))
    d = d.withColumn("lc_hashes", F.expr("transform(lc_lines, x -> xxhash64(x))"))
    rolled = f"pmod(shiftright(shiftleft(lc_hashes[i - 1], 1) ^ lc_hashes[i], 7), {modulus})"
    ends = F.expr(f"filter(sequence(0, size(lc_lines) - 1), i -> i = size(lc_lines) - 1 OR (i > 0 AND {rolled} = 0))")
    return d.withColumn("lc_ends", ends)


#: A piece is a range of lines, as the number of its first line times WIDE plus how many lines it has.
WIDE = 1 << 32


def piece(code: str, of: str = "lc_lines") -> str:
    """SQL for the lines (or what else there is one of for each line) of a piece."""
    return f"slice({of}, CAST({code} div {WIDE} AS INT) + 1, CAST({code} % {WIDE} AS INT))"


def pieces(runs: bool) -> str:
    """SQL for the pieces of lc_lines that count: of two lines or more, with a word.

    They are the chunks and, with runs, each two neighbouring lines that are not blank, with the blank lines between
    them, and the whole text if it has blank lines at an end. A shared run of lines is made of such twos, wherever the chunks' boundaries are.
    """
    start = "IF(j = 0, 0, lc_ends[greatest(j, 1) - 1] + 1)"
    chunks = f"transform(sequence(0, size(lc_ends) - 1), j -> {start} * {WIDE} + lc_ends[j] - {start} + 1)"
    word = "length(trim(array_join({}, ''))) > 0"
    if not runs:
        return f"filter({chunks}, c -> c % {WIDE} > 1 AND {word.format(piece('c'))})"
    full = "filter(sequence(0, size(lc_lines) - 1), i -> length(trim(lc_lines[i])) > 0)"
    twos = f"zip_with(f, slice(f, 2, size(f)), (a, b) -> a * {WIDE} + b - a + 1)"
    # a text that begins and ends with a word is covered by its twos
    edges = "size(f) > 0 AND size(lc_lines) > 1 + try_element_at(f, -1) - try_element_at(f, 1)"
    # the last of f has no line after it: null, left out by the filter
    known = f"transform(array({full}), f -> concat({twos}, filter({chunks}, c -> {word.format(piece('c'))}), IF({edges}, array(CAST(size(lc_lines) AS BIGINT)), array())))[0]"
    return f"array_distinct(filter({known}, c -> c % {WIDE} > 1))"


def piece_hashes(rows: DataFrame, modulus: int, runs: bool) -> DataFrame:
    """lc_doc, lc_row, lc_no (the piece) and lc_hash of each piece that counts."""
    d = chunk_columns(rows, modulus).withColumn("lc_nos", F.expr(pieces(runs)))
    hashed = F.expr(f"transform(lc_nos, c -> struct(c AS lc_no, xxhash64({piece('c', 'lc_hashes')}) AS lc_hash))")
    return d.select("lc_doc", "lc_row", F.inline(hashed))


def repeated_pieces(rows: DataFrame, modulus: int = MODULUS, runs: bool = False) -> DataFrame:
    """lc_doc, lc_row and lc_nos: the pieces to remove from each row.

    1. Count the pieces' hashes; most stand once and go no further.
    2. The lines of the others come from the texts, and are grouped by themselves, which compares their bytes. The
       smallest doc_id of a piece has its first place, there at the smallest line.
    3. All other places are removed.
    """
    hashes = piece_hashes(rows.select("lc_doc", "lc_row", "text"), modulus, runs)
    # written first, so that both sides of the join come by an exchange and a frequent piece's side can be split
    often = written(hashes.groupBy("lc_hash").agg(F.count("*").alias("lc_n")).filter("lc_n > 1").select("lc_hash"), "chunk-hashes")
    places = hashes.join(often, "lc_hash", "left_semi").groupBy("lc_doc", "lc_row").agg(F.collect_set("lc_no").alias("lc_nos"))
    texts = rows.join(places, ["lc_doc", "lc_row"]).withColumn("lc_lines", F.split(F.coalesce(F.col("text"), F.lit("")), "\n", -1))
    texts = texts.select("lc_doc", "lc_row", F.explode("lc_nos").alias("lc_no"), "lc_lines")
    texts = written(texts.select("lc_doc", "lc_row", "lc_no", F.expr(f"array_join({piece('lc_no')}, '\n')").alias("lc_text")), "chunk-texts")
    first = written(texts.groupBy("lc_text").agg(F.min("lc_doc").alias("lc_first"), F.count("*").alias("lc_n")).filter("lc_n > 1").select("lc_text", "lc_first"), "first-places")
    both = texts.join(first, "lc_text")
    # the places of one text in its first document: no more than the document has pieces
    own = both.filter("lc_doc = lc_first").groupBy("lc_doc", "lc_text").agg(F.sort_array(F.collect_set(F.struct("lc_row", "lc_no"))).alias("x"))
    own = own.select("lc_doc", F.explode(F.expr("slice(x, 2, size(x))")).alias("y")).select("lc_doc", "y.lc_row", "y.lc_no")
    gone = both.filter("lc_doc <> lc_first").select("lc_doc", "lc_row", "lc_no").unionByName(own)
    return gone.groupBy("lc_doc", "lc_row").agg(F.collect_set("lc_no").alias("lc_nos"))


def drop_repeated_chunks(docs: DataFrame, modulus: int = MODULUS, runs: bool = False) -> DataFrame:
    """docs, all columns, without the chunks of several lines that stand elsewhere before; adds lc_removed_chunks and lc_removed_lines.

    The first place of a chunk is in the smallest doc_id that has it. Only chunks of two lines or more with a word in
    them count. Null text stays null, empty text empty, and an empty table gives an empty one. A long text is one row of
    lines. Rows without a doc_id are left as they are and are no first
    place. Equal rows are one document. Columns whose names start with lc_ are replaced. No Python runs: split, hash,
    group and join are Spark's. A chunk that a third of all documents hold is one row for each task before it is
    shuffled, and joins with one row on the other side, so its large side can be split.

    With runs, each run of two lines or more that stood before goes (blank lines between count as part of it, not as
    lines), also where it holds no whole chunk, and each whole text of several lines that stood before. A line that goes
    has an earlier place, so each stays once. lc_removed_chunks has the chunks of which no line is left.
    """
    docs = docs.drop(*[c for c in docs.columns if c.startswith("lc_")])
    rows = with_row(docs)
    gone = repeated_pieces(rows, modulus, runs)
    d = chunk_columns(rows.join(gone, ["lc_doc", "lc_row"], "left"), modulus).drop("lc_hashes")
    out = f"flatten(transform(lc_nos, c -> sequence(CAST(c div {WIDE} AS INT), CAST(c div {WIDE} + c % {WIDE} - 1 AS INT))))"
    d = d.withColumn("lc_kept", F.expr(f"IF(lc_nos IS NULL, NULL, array_except(sequence(0, size(lc_lines) - 1), {out}))"))
    text = F.when(F.col("lc_nos").isNull(), F.col("text")).otherwise(F.expr("array_join(transform(lc_kept, i -> lc_lines[i]), '\n')"))
    # the chunk of each line
    numbers = "flatten(transform(sequence(0, size(lc_ends) - 1), j -> array_repeat(j, lc_ends[j] - IF(j = 0, -1, lc_ends[greatest(j, 1) - 1]))))"
    chunks = F.expr(f"size(lc_ends) - size(array_distinct(transform(array({numbers}), n -> transform(lc_kept, i -> n[i]))[0]))")
    counts = [F.when(F.col("lc_nos").isNull(), 0).otherwise(x).cast("long").alias(f"lc_removed_{name}") for name, x in (("chunks", chunks), ("lines", F.expr("size(lc_lines) - size(lc_kept)")))]
    # doc_id is read off lc_doc: with doc_id and text alone, the texts are dealt out once for both joins
    named = {"text": text, "doc_id": F.col("lc_doc")}
    # by a generator, through which no later filter is pushed: inside it, lines would be split anew for each of them
    done = d.select(F.inline(F.array(F.struct(*[named.get(c, F.col(f"`{c}`")).alias(c) for c in docs.columns], *counts))))
    rest = docs.filter("doc_id IS NULL").select(*docs.columns, F.lit(0).cast("long").alias("lc_removed_chunks"), F.lit(0).cast("long").alias("lc_removed_lines"))
    return done.unionByName(rest)
