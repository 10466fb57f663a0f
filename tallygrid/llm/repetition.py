"""Quality rule on repetition: suffix arrays of words find what a text says twice.

Many documents share one suffix array: a suffix's first rank is its (document, word), so suffixes of different documents never compare
equal, and ranks double their reach until all are told apart; only suffixes that are still tied are sorted again. The ranks of
each round also give the longest common prefix of neighbours. The deepest LCP interval that holds a suffix has the larger of its
two neighbours' prefixes as its length; the intervals above it hold prefixes of that span. So the union of these spans, from
`least` words on, is the union of all maximal repeats' occurrences.

A text is kept if it has enough words, and if repeats cover at most a given share of its words (the base rule, windows of five
words) and of its characters, and if its longest repeat has at most `longest` words.

Defined results: null, empty and blank texts have 0 words and fail the base rule; repeated rows are judged alike; an empty table gives
an empty result; only doc_id and text are read, so further columns may have any name.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import WordIds, pieces, table, texts

#: The characters that count as symbols, the class that splits words, and the base rule's numbers.
SYMBOLS, SPACES = b"#*$%&|<>", b"\x09\x0a\x0b\x0c\x0d\x20"
LEAST_WORDS, WINDOW, BASE_PERCENT = 10, 5, 20
#: The method's limits: share of a text's word characters under repeats, and words of the longest repeat.
COVERED, LONGEST = 0.25, 32

SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, covered_chars long, longest_repeat long, base_failed boolean, kept boolean"

_IS_SYMBOL = np.zeros(256, dtype=np.int64)
_IS_SYMBOL[list(SYMBOLS)] = 1
_IN_WORD = np.ones(256, dtype=np.int64)
_IN_WORD[list(SPACES)] = 0
_IN_WORD[0x80:0xC0] = 0  # later bytes of a character


def longest_matches(ids: np.ndarray, doc: np.ndarray, least: int) -> np.ndarray:
    """For each position, the words that its suffix shares with another suffix of its document; 0 where under `least`."""
    n = len(ids)
    matches = np.zeros(n, dtype=np.int64)
    if n < 2:
        return matches
    key = doc.astype(np.int64) * (int(ids.max()) + 1) + ids
    order = np.argsort(key, kind="stable")
    new = np.empty(n, dtype=bool)
    new[0], new[1:] = True, key[order][1:] != key[order][:-1]
    rank = np.empty(n, dtype=np.int64)
    rank[order] = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    levels, reach = [], 1
    tied = ~new
    tied[:-1] |= ~new[1:]
    active = order[tied]  # in the order of rank
    while len(active):
        levels.append((reach, rank.astype(np.int32)))
        ahead = active + reach
        inside = ahead < n
        ahead = np.minimum(ahead, n - 1)
        second = np.where(inside & (doc[ahead] == doc[active]), rank[ahead], -1)
        first = rank[active]
        again = np.lexsort((second, first))
        active, first, second = active[again], first[again], second[again]
        head = np.empty(len(active), dtype=bool)
        head[0], head[1:] = True, first[1:] != first[:-1]
        split = head.copy()
        split[1:] |= second[1:] != second[:-1]
        at = np.arange(len(active))
        base = np.maximum.accumulate(np.where(head, at, 0))
        order[first + at - base] = active
        rank[active] = first + np.maximum.accumulate(np.where(split, at, 0)) - base
        tied = ~split
        tied[:-1] |= ~split[1:]
        active = active[tied]
        reach *= 2
    # Neighbours in suffix order whose first words are alike; their common prefix from the largest power of two down.
    left, right = order[:-1], order[1:]
    floor = 1 << max(0, least.bit_length() - 1)
    low = next((r for h, r in levels if h == floor), None)
    if low is None:
        return matches
    pair = np.flatnonzero(low[left] == low[right])
    a, b = left[pair], right[pair]
    common = np.zeros(len(pair), dtype=np.int64)
    for h, r in reversed(levels):
        x, y = a + common, b + common
        inside = (x < n) & (y < n)
        x, y = np.minimum(x, n - 1), np.minimum(y, n - 1)
        fits = inside & (doc[x] == doc[a]) & (doc[y] == doc[b]) & (r[x] == r[y])
        common += np.where(fits, h, 0)
    np.maximum.at(matches, a, common)
    np.maximum.at(matches, b, common)
    matches[matches < least] = 0
    return matches


def _sums(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    total = np.concatenate(([0], np.cumsum(values, dtype=np.int64)))
    return total[ends] - total[starts]


def measure(found: list[bytes | None]) -> dict[str, np.ndarray]:
    """The columns of SCHEMA, without doc_id and verdicts, for a block of texts."""
    words, ids, counts, dup = WordIds(), [], [], []
    look = words.__getitem__
    for text in found:
        own = list(map(look, text.split())) if text else []
        ids += own
        counts.append(len(own))
        lines = [x for x in text.split(b"\n") if x and not x.isspace()] if text else []
        dup.append(len(lines) - len(set(lines)))
    count = np.asarray(counts, dtype=np.int64)
    ends = np.cumsum(count)
    starts = ends - count
    doc = np.repeat(np.arange(len(found)), count)
    ids = np.asarray(ids, dtype=np.int64)
    matches = longest_matches(ids, doc, WINDOW)
    at = np.flatnonzero(matches)
    cover = np.zeros(len(ids) + 1, dtype=np.int64)
    cover[at] += 1
    np.subtract.at(cover, at + matches[at], 1)
    covered = np.cumsum(cover)[:-1] > 0
    joined = np.frombuffer(b"".join(t or b"" for t in found), dtype=np.uint8)
    size = np.asarray([len(t or b"") for t in found], dtype=np.int64)
    to = np.cumsum(size)
    chars = np.asarray([len(w) - sum(0x80 <= c < 0xC0 for c in w) if not w.isascii() else len(w) for w in words.words], dtype=np.int64)
    each = chars[ids] if len(ids) else ids
    longest = np.zeros(len(found), dtype=np.int64)
    np.maximum.at(longest, doc, matches)
    return {
        "n_words": count, "word_chars": _sums(_IN_WORD[joined], to - size, to), "n_symbols": _sums(_IS_SYMBOL[joined], to - size, to), "n_dup_lines": np.asarray(dup, dtype=np.int64),
        "n_repeat_words": _sums(covered, starts, ends), "covered_chars": _sums(np.where(covered, each, 0), starts, ends), "longest_repeat": longest,
    }


def judge(docs: DataFrame, covered: float = COVERED, longest: int = LONGEST) -> DataFrame:
    """One row of SCHEMA per row of `docs`."""

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in pieces(batches):
            m = measure(texts(piece.column("text")))
            failed = (m["n_words"] < LEAST_WORDS) | (100 * m["n_repeat_words"] > BASE_PERCENT * m["n_words"])
            kept = ~failed & (m["covered_chars"] <= covered * m["word_chars"]) & (m["longest_repeat"] <= longest)
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), *map(pa.array, m.values()), pa.array(failed), pa.array(kept)], names=["doc_id", *m, "base_failed", "kept"])

    return docs.selectExpr("CAST(doc_id AS BIGINT) AS doc_id", "text").mapInArrow(blocks, SCHEMA)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents", "doc_id", "text"))
