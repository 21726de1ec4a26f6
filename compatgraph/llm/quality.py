"""Quality rules with a distribution-divergence verdict.

Base counts follow fixed rules.  The method compares a document's histogram of character classes and its
histogram of common words with references by the Jensen-Shannon distance (base 2, 0 to 1).  References are the mean
histograms of each ``lang`` over the documents that pass the base rule; langs of less than one in ``LANGS`` of these share one reference, so
their number is bounded however dirty the column is.  The means are sums of whole numbers (shares in units of 1 / ``UNIT``), so they don't
depend on the order of tasks and reruns agree.  A document is held against one reference, that with the least sum of both
distances, whatever its own ``lang`` says.  It is odd by its characters alone (above ``max_char``), by its words alone (above ``max_word``), or by
both at once (above ``BOTH``), which tells tables of words from text.  Guards: the character test needs ``min_chars``
characters, the word test ``min_words`` words, the joint test ``BOTH_WORDS`` words, since the histograms of short texts
are far from any reference by chance; shorter documents pass that test.

Null texts have no words and fail the base rule.  Null langs are one lang more.  Rows are judged on
their own, so repeated rows get equal verdicts; an empty table gives an empty result; very long texts are read whole; other columns,
whatever their names, are passed on by ``keep`` and not read.
"""

from __future__ import annotations

import sys
import unicodedata
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import col, map_text, materialise, narrow, texts

WHITE, SYMBOLS = b" \t\n\v\f\r", b"#*$%&|<>"
# Common function words of the four languages of the tables.
COMMON = (
    "the of and to in a is that for it was on are as with be by this from or at an have not you which "
    "der die das und ist in den von zu mit sich des auf für nicht ein eine als auch es an werden aus er hat "
    "le la les de des et un une est en que qui dans pour pas au sur par il ce plus ne se son avec "
    "el los las del y que una por con para su no al lo como más pero sus le ya o este sí porque esta"
).split()
INDEX = {w.encode(): i for i, w in enumerate(dict.fromkeys(COMMON))}
N_WORDS = len(INDEX) + 1
N_CLASSES = 8
#: Joint test: distances of characters and of words that clean text seldom reaches together, and the words it needs.
BOTH, BOTH_WORDS = (0.13, 0.28), 50
LANGS, UNIT = 64, 1 << 20


def _classes() -> np.ndarray:
    """Class of each code point: lower, upper, digit, white space, sentence marks, symbols of the base rule, other, letters without case."""
    of = {"Ll": 0, "Lu": 1, "Lt": 1, "Nd": 2, "Zs": 3, "Zl": 3, "Zp": 3, "Po": 4, "Pd": 4, "Pi": 4, "Pf": 4, "Lo": 7, "Lm": 7, "Mn": 7, "Mc": 7}
    out = np.full(0x10000, 6, np.uint8)  # beyond it there are few letters and many symbols
    for i in range(128, 0x10000):
        out[i] = of.get(unicodedata.category(chr(i)), 6)
    for chars, k in (("abcdefghijklmnopqrstuvwxyz", 0), ("ABCDEFGHIJKLMNOPQRSTUVWXYZ", 1), ("0123456789", 2), (WHITE.decode(), 3), (".,;:!?'\"()-", 4), (SYMBOLS.decode(), 5)):
        out[[ord(c) for c in chars]] = k
    return out


CLASS = _classes()
_UTF32 = "utf-32-le" if sys.byteorder == "little" else "utf-32-be"


def repeat_words(words: list[bytes], k: int = 5) -> int:
    """Words inside ``k``-word windows that occur twice or more."""
    windows = list(zip(*[words[i:] for i in range(k)], strict=False))
    if len(set(windows)) == len(windows):
        return 0
    seen: dict[tuple, int] = {}
    for w in windows:
        seen[w] = seen.get(w, 0) + 1
    covered, until = 0, 0
    for i, w in enumerate(windows):
        if seen[w] > 1:
            covered += i + k - max(i, until)
            until = i + k
    return covered


def base_counts(raw: bytes) -> tuple[list[bytes], int, int, int, int]:
    """Words, and word_chars, n_symbols, n_dup_lines, n_repeat_words of a UTF-8 text."""
    words = raw.split()
    starts = raw.translate(None, bytes(range(128, 192)))  # one byte a code point
    lines = [x for x in raw.split(b"\n") if x.strip()]
    return words, len(starts.translate(None, WHITE)), len(raw) - len(raw.translate(None, SYMBOLS)), len(lines) - len(set(lines)), repeat_words(words)


def histograms(text: str, raw: bytes, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Shares of character classes, and of each common word and of all other words."""
    if len(text) == len(raw):
        points = np.frombuffer(raw, np.uint8)
    else:
        points = np.minimum(np.frombuffer(text.encode(_UTF32), np.uint32), 0xFFFF)
    chars = np.bincount(CLASS[points], minlength=N_CLASSES).astype(float)
    lowered = words if raw.islower() else raw.lower().split()
    hits = [i for i in map(INDEX.get, lowered) if i is not None]
    common = np.bincount(hits, minlength=N_WORDS).astype(float)
    common[-1] = len(words) - len(hits)
    return chars / max(1, len(text)), common / max(1, len(words))


def js_distances(p: np.ndarray, refs: np.ndarray) -> np.ndarray:
    """Jensen-Shannon distance of ``p`` from each row of ``refs``."""
    m = (p + refs) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        a = np.where(p > 0, p * np.log2(p / m), 0).sum(1)
        b = np.where(refs > 0, refs * np.log2(refs / m), 0).sum(1)
    return np.sqrt(np.maximum(0.0, (a + b) / 2))


def nearest(chars: np.ndarray, common: np.ndarray, refs: tuple[np.ndarray, np.ndarray]) -> tuple[float, float]:
    """Distances of characters and words from the one reference nearest in both together; 0 without references."""
    if not len(refs[0]):
        return 0.0, 0.0
    c, w = js_distances(chars, refs[0]), js_distances(common, refs[1])
    best = int(np.argmin(c + w))
    return float(c[best]), float(w[best])


def base_fails(n: int, repeat: int) -> bool:
    return n < 10 or 100 * repeat > 20 * n


def references(docs: DataFrame, *, min_words: int = 50) -> dict[str, list[list[float]]]:
    """Mean histograms by lang over all documents of ``min_words`` words or more that pass the base rule: ``LANGS`` + 1 rows at most reach the driver."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch | None:
        sums: dict = {}
        for text, lang in zip(texts(batch), col(batch, "lang").to_pylist(), strict=True):
            raw = text.encode()
            words = raw.split()
            if len(words) >= min_words and not base_fails(len(words), repeat_words(words)):
                h = np.concatenate([np.rint(np.concatenate(histograms(text, raw, words)) * UNIT), [1]]).astype(np.int64)
                sums[lang] = sums[lang] + h if lang in sums else h
        return pa.RecordBatch.from_pydict({"lang": pa.array(list(sums), pa.string()), "h": pa.array([s.tolist() for s in sums.values()], pa.list_(pa.int64()))})

    names = [f"h{i}" for i in range(N_CLASSES + N_WORDS + 1)]
    partial = map_text(narrow(docs, "text", "lang"), run, "lang string, h array<long>")
    sums = materialise(partial.groupBy("lang").agg(*[F.sum(F.element_at("h", i + 1)).alias(x) for i, x in enumerate(names)]), "quality-langs")
    total = sums.agg(F.sum(names[-1])).first()[0] or 0
    own = F.col(names[-1]) * LANGS >= total
    grouped = sums.groupBy(own.alias("own"), F.when(own, F.col("lang")).alias("lang")).agg(*[F.sum(x).alias(x) for x in names])
    means = [np.array(r[2:-1]) / (r[-1] * UNIT) for r in sorted(grouped.collect(), key=lambda r: (r.own, r.lang is not None, r.lang or "")) if r[-1]]
    return {"chars": [m[:N_CLASSES].tolist() for m in means], "words": [m[N_CLASSES:].tolist() for m in means]}


NAMES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "char_js", "word_js", "kept"]


def _judge(batch: pa.RecordBatch, refs: dict, min_chars: int, min_words: int, max_char: float, max_word: float) -> list[tuple]:
    both = np.array(refs["chars"]), np.array(refs["words"])
    rows = []
    for text in texts(batch):
        raw = text.encode()
        words, *counts = base_counts(raw)
        n = len(words)
        failed = base_fails(n, counts[3])
        c, w = nearest(*histograms(text, raw, words), both)
        odd = len(text) >= min_chars and c > max_char or n >= min_words and w > max_word or n >= BOTH_WORDS and c > BOTH[0] and w > BOTH[1]
        rows.append((n, *counts, failed, c, w, not failed and not odd))
    return rows


def judge(docs: DataFrame, refs: dict | None = None, *, min_chars: int = 200, min_words: int = 75, max_char: float = 0.30, max_word: float = 0.30) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, char_js, word_js, kept."""
    refs = refs or references(docs)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = _judge(batch, refs, min_chars, min_words, max_char, max_word)
        arrays = [pa.array(x, t) for x, t in zip(zip(*rows, strict=True), chain([pa.int64()] * 5, [pa.bool_(), pa.float64(), pa.float64(), pa.bool_()]), strict=True)]
        return pa.RecordBatch.from_arrays([col(batch, "doc_id"), *arrays], names=["doc_id", *NAMES])

    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, char_js double, word_js double, kept boolean"
    return map_text(narrow(docs, "doc_id", "text"), run, schema)


def keep(docs: DataFrame, refs: dict | None = None, *, min_chars: int = 200, min_words: int = 75, max_char: float = 0.30, max_word: float = 0.30) -> DataFrame:
    """The rows of ``docs`` that ``judge`` keeps, with all their columns: a map, no shuffle."""
    refs = refs or references(docs)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        return batch.filter(pa.array([r[-1] for r in _judge(batch, refs, min_chars, min_words, max_char, max_word)], pa.bool_()))

    return map_text(docs, run, docs.schema)
