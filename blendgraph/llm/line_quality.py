"""Line-first cleaning: rules judge lines, failing lines go, documents that lose too much go."""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import per_batch, utf8

# fixed values
SYMBOLS = b"#*$%&|<>"
ENDINGS = (".", "!", "?", "…", "。", "！", "？", "؟", "।", ":", ";")
CLOSERS = "\"'”’»)]*_"
SEPARATORS = re.compile(r"[|»›•·]|\s[>/]\s")
BOILERPLATE = re.compile(
    r"cookie|javascript|all rights reserved|privacy policy|terms of (?:use|service)|sign up|log ?in\b|subscribe|click here"
    r"|read more|share this|follow us|powered by|lorem ipsum|back to top|skip to content"
    r"|alle rechte vorbehalten|datenschutzerklärung|nutzungsbedingungen|weiterlesen|hier klicken|newsletter abonnieren|zum inhalt springen"
    r"|tous droits réservés|politique de confidentialité|conditions d.utilisation|lire la suite|cliquez ici|abonnez-vous|aller au contenu"
    r"|todos los derechos reservados|política de privacidad|términos de uso|leer más|haga clic aquí|suscríbete|ir al contenido",
    re.IGNORECASE,
)
SPACE = b" \t\n\r\x0b\x0c"
#: Bytes of a text up to which its words are held as they are.
PIECE = 1 << 20
NO_CHAR = SPACE + bytes(range(0x80, 0xC0))  # white space, and the bytes that continue a character


@dataclass(frozen=True)
class LineRules:
    """Limits of the rules. A line fails if it has many symbols, is navigation or boilerplate, or is short and ends
    without punctuation. A document is rejected if under min_kept of its words stay."""

    max_symbols_per_word: float = 0.5
    short_line: int = 12
    boilerplate_words: int = 25
    min_kept: float = 0.5
    min_words: int = 10
    max_repeat_percent: int = 20


def line_failure(line: str, rules: LineRules = LineRules()) -> str | None:
    """Name of the first rule that the line fails, or None. A line without a word is no line and fails none."""
    n = len(line.encode("utf-8", "replace").split())
    if not n:
        return None
    marks = sum(line.count(c) for c in "#*$%&|<>")
    if len(SEPARATORS.findall(line)) >= 2 and n <= 6 * (1 + len(SEPARATORS.findall(line))):
        return "navigation"
    if marks > rules.max_symbols_per_word * n:
        return "symbols"
    if n <= rules.boilerplate_words and BOILERPLATE.search(line):
        return "boilerplate"
    if n < rules.short_line and not line.rstrip(" \t\n\r\x0b\x0c").rstrip(CLOSERS).endswith(ENDINGS):
        return "punctuation"
    return None


def repeat_words(words: list[bytes]) -> int:
    """Words in windows of five that stand twice or more."""
    windows = list(zip(words, words[1:], words[2:], words[3:], words[4:]))
    repeated = 0
    if len(set(windows)) < len(windows):
        often, covered = Counter(windows), 0
        for i, window in enumerate(windows):
            if often[window] > 1:
                repeated += i + 5 - max(covered, i)
                covered = i + 5
    return repeated


def long_repeat_words(text: bytes) -> tuple[int, int]:
    """Number of words and repeat_words of a long text, in a few numbers a word: words are numbered piece by piece, and
    windows by the ranks of their halves, which are equal where the windows are."""
    numbers: dict[bytes, int] = {}
    parts, at = [], 0
    while at < len(text):
        end = at + PIECE
        while end < len(text) and text[end] not in SPACE:
            end += 1
        parts.append(np.fromiter((numbers.setdefault(w, len(numbers)) for w in text[at:end].split()), np.int64))
        at = end
    x = np.concatenate(parts) if parts else np.zeros(0, np.int64)
    if len(x) < 5:
        return len(x), 0
    rank = x
    for k in range(1, 5):
        rank = np.unique(rank[:-1] * len(numbers) + x[k:], return_inverse=True)[1]
    often = np.bincount(rank)[rank] > 1
    covered = np.zeros(len(x), bool)
    for k in range(5):
        covered[k : k + len(often)] |= often
    return len(x), int(covered.sum())


def base_counts(text: bytes) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines and n_repeat_words of a whole text."""
    seen: set[bytes] = set()
    dup_lines = 0
    for line in text.split(b"\n"):
        # of a long line its hash is kept
        key = line if len(line) < 64 else hashlib.blake2b(line, digest_size=32).digest()
        if key in seen:
            dup_lines += 1
        elif line.strip():
            seen.add(key)
    del seen
    if len(text) > PIECE:
        n_words, repeated = long_repeat_words(text)
    else:
        words = text.split()  # bytes split at ASCII white space alone
        n_words, repeated = len(words), repeat_words(words)
    n_symbols = len(text) - len(text.translate(None, SYMBOLS))
    return n_words, len(text.translate(None, NO_CHAR)), n_symbols, dup_lines, repeated


def clean_text(text: str, rules: LineRules = LineRules()) -> tuple[str, int, int]:
    """The text without its failing lines, how many failed, and the words that stayed."""
    kept, failed, words = [], 0, 0
    for line in text.split("\n"):
        if line_failure(line, rules):
            failed += 1
        else:
            kept.append(line)
            words += len(line.encode("utf-8", "replace").split())
    return "\n".join(kept), failed, words


def judge(text: bytes, rules: LineRules) -> tuple:
    n_words, word_chars, n_symbols, n_dup, n_repeat = base_counts(text)
    bad = n_words < rules.min_words or 100 * n_repeat > rules.max_repeat_percent * n_words
    cleaned, failed, stay = clean_text(text.decode("utf-8", "replace"), rules)
    kept = not bad and stay >= rules.min_kept * n_words
    return n_words, word_chars, n_symbols, n_dup, n_repeat, bad, kept, failed, stay, cleaned


MEASURES = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, n_failed_lines long, n_kept_words long"


def score_quality(docs: DataFrame, rules: LineRules = LineRules()) -> DataFrame:
    """doc_id, the counts of the base, base_failed, kept, and what the line rules found. One pass, no shuffle.

    Null text counts as empty: no words, so base_failed. Repeated rows are judged each. Other columns are ignored. An
    empty table gives no rows. A text of over PIECE bytes is counted in a few numbers a word.
    """
    kinds = [pa.int64()] * 5 + [pa.bool_()] * 2 + [pa.int64()] * 2
    names = [x.split()[0] for x in MEASURES.split(", ")]

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = [judge(t or b"", rules)[:-1] for t in utf8(batch.column(1))]
        cols = zip(*rows) if rows else [[]] * len(names)
        return pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds))], ["doc_id", *names])

    d = docs.select("doc_id", "text")
    return d.mapInArrow(per_batch(run), f"doc_id {d.schema['doc_id'].dataType.simpleString()}, {MEASURES}")


def clean_documents(docs: DataFrame, rules: LineRules = LineRules()) -> DataFrame:
    """The documents that are kept, with all columns, without their failing lines. n_chars, if there, is counted anew.

    Null and empty texts have no words and go. Repeated rows are judged each; no column name is reserved; an empty table
    gives an empty one."""
    at, counted = docs.columns.index("text"), docs.columns.index("n_chars") if "n_chars" in docs.columns else None

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = [judge(t or b"", rules) for t in utf8(batch.column(at))]
        keep = [r[6] for r in rows]
        batch = batch.filter(pa.array(keep, pa.bool_()))
        texts = [r[-1] for r in rows if r[6]]
        cols = batch.columns
        cols[at] = pa.array(texts, batch.schema.field(at).type)
        if counted is not None:
            cols[counted] = pa.array([len(t) for t in texts], pa.int64()).cast(batch.schema.field(counted).type)
        return pa.RecordBatch.from_arrays(cols, schema=batch.schema)

    return docs.mapInArrow(per_batch(run), docs.schema)
