"""Language of words in code-switched text, by a linear-chain conditional random field.

A word's features are the n-grams of its letters with marks at both ends (so that affixes are n-grams too), the whole word, and whether it stands in
the lexicon of a language. Their weights and the transitions between languages are learned together, by the gradient of the
sequences' likelihood. Labels are known for documents only, so training sequences are made by joining runs of words from different documents,
which is where transitions are learned from. Words are then labelled by forward-backward, and a document by the mean of its words'
marginals.

A sequence is a line, cut after `SPAN` words; every word of the text is in one. Many sequences run side by side. The model is fitted
on a bounded sample of documents outside the held-out fold: about `sample_docs`, as many of each language as of another where there are so many, chosen by hash. A text of any
length teaches with `DRAWN` words, in runs of `RUN` from its beginning to its end, so what the driver gets is bounded; all texts are labelled whole.

Defined results: null texts and texts without a letter are `und` with score 0; so are all texts if no language can be learned; ties go
to the language that sorts first; repeated rows are labelled alike; an empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import WordIds, held_out, pieces, sampled, table, texts

SAMPLE_DOCS, SAMPLE_WORDS, DRAWN, RUN = 2_000, 120_000, 480, 12
BITS, ORDERS, SPAN, STEPS = 17, (1, 2, 3, 4), 128, 40
LEXICON, LEXICON_COUNT = 1_000, 5
#: ASCII: letters in lower case, line ends kept, all else but later bytes of UTF-8 a blank.
_LETTERS = bytes(b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 or b == 10 else 32 for b in range(256))
_M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def letters(word: bytes) -> bytes:
    """The word's letters in lower case; empty if there are none."""
    if word.isascii():
        return word
    return "".join(c for c in word.decode("utf-8", "ignore").lower() if c.isalpha()).encode()


def ngrams(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(word, feature) of all n-grams of the marked words, and of the words as a whole, in word order inside each kind."""
    flat = np.frombuffer(b"".join(b"^" + w + b"$" for w in words), dtype=np.uint8).astype(np.uint64)
    size = np.asarray([len(w) + 2 for w in words], dtype=np.int64)
    end = np.cumsum(size)
    owner = np.repeat(np.arange(len(words)), size)
    left = np.repeat(end, size) - np.arange(len(flat))
    rows, cols, code = [], [], np.zeros(len(flat), dtype=np.uint64)
    for order in range(1, max(ORDERS) + 1):
        code[: len(flat) - order + 1] = code[: len(flat) - order + 1] * _M1 + flat[order - 1 :] + np.uint64(order)
        at = np.flatnonzero(left >= order)
        mixed = (code[at] ^ (code[at] >> np.uint64(29))) * _M2
        rows.append(owner[at])
        cols.append((mixed >> np.uint64(64 - BITS)).astype(np.int64))
    place = np.arange(len(flat)) - np.repeat(end - size, size)
    powers = np.ones(int(size.max()) if len(size) else 1, dtype=np.uint64)
    powers[1:] = np.cumprod(np.full(len(powers) - 1, _M1, dtype=np.uint64))
    whole = np.add.reduceat(flat * powers[place], end - size) if len(words) else np.empty(0, np.uint64)
    rows.append(np.arange(len(words)))
    cols.append((((whole ^ (whole >> np.uint64(31))) * _M2) >> np.uint64(64 - BITS)).astype(np.int64))
    return np.concatenate(rows), np.concatenate(cols)


@dataclass
class Field:
    """weights: features by labels; lexicon: word -> label whose lexicon has it; in_lexicon: its weights; moves, first: log scores."""

    labels: list[str]
    weights: np.ndarray
    lexicon: dict[bytes, int]
    in_lexicon: np.ndarray
    moves: np.ndarray
    first: np.ndarray

    def emissions(self, words: list[bytes], block: int = 60_000) -> np.ndarray:
        """labels by words, log scores; the mean over a word's n-grams, so that long words weigh no more."""
        out = np.empty((len(self.labels), len(words)), dtype=np.float32)
        for a in range(0, len(words), block):
            own = words[a : a + block]
            row, col = ngrams(own)
            share = np.bincount(row, minlength=len(own))
            for k in range(len(self.labels)):
                out[k, a : a + len(own)] = np.bincount(row, weights=self.weights[k][col], minlength=len(own)) / np.sqrt(share)
            known = np.asarray([self.lexicon.get(w, -1) for w in own])
            hit = np.flatnonzero(known >= 0)
            out[:, a + hit] += self.in_lexicon[:, known[hit]]
        return out


def marginals(emission: np.ndarray, moves: np.ndarray, first: np.ndarray, start: np.ndarray, length: np.ndarray, pairs: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """Forward-backward for sequences side by side.

    emission: labels by words, log. Sequences are words start .. start + length - 1. Gives the words' marginals, the log likelihood's
    scale of each sequence, and with `pairs` the expected transitions in all.
    """
    m = len(first)
    order = np.argsort(-length, kind="stable")
    start, length = start[order], length[order]
    top = emission.max(axis=0)
    e = np.exp(emission - top)
    step = np.exp(moves - moves.max())
    longest = int(length[0]) if len(length) else 0
    active = np.searchsorted(-length, -np.arange(longest), side="left")  # sequences longer than t
    forward = np.empty_like(e)
    log_scale = np.zeros(len(start))
    a = None
    for t in range(longest):
        n = active[t]
        at = start[:n] + t
        a = (np.exp(first - first.max())[:, None] if t == 0 else step.T @ a[:, :n]) * e[:, at]
        total = a.sum(axis=0)
        a = a / total
        forward[:, at] = a
        log_scale[:n] += np.log(total) + top[at]
    out = np.empty_like(e)
    expected = np.zeros((m, m)) if pairs else None
    b = np.ones((m, len(start)), dtype=e.dtype)
    for t in range(longest - 1, -1, -1):
        n = active[t]
        at = start[:n] + t
        g = forward[:, at] * b[:, :n]
        g /= g.sum(axis=0)
        out[:, at] = g
        if t:
            ahead = e[:, at] * b[:, :n]
            if pairs:
                before = forward[:, at - 1]
                both = step @ ahead
                total = (before * both).sum(axis=0)
                expected += step * ((before / total) @ ahead.T)
            b[:, :n] = step @ ahead
            b[:, :n] /= b[:, :n].sum(axis=0)
    back = np.empty_like(log_scale)
    back[order] = log_scale
    return out, back, expected


def train(documents: list[tuple[bytes, str]], steps: int = STEPS, most_words: int = SAMPLE_WORDS, seed: int = 5) -> Field | None:
    """Learn from (text, language) pairs; None if no document has a word."""
    rng = np.random.default_rng(seed)
    tokenised = [(w, lang) for text, lang in documents if (w := [x for x in map(letters, text.translate(_LETTERS).split()) if x])]
    if not tokenised:
        return None
    labels = sorted({lang for _, lang in tokenised})
    index = {lang: k for k, lang in enumerate(labels)}
    counts = [Counter() for _ in labels]
    for words, lang in tokenised:
        counts[index[lang]].update(words)
    totals = np.asarray([sum(c.values()) for c in counts], dtype=np.float64)
    lexicon: dict[bytes, int] = {}
    for k, c in enumerate(counts):
        rate = lambda w, j: (counts[j][w] + 0.5) / (totals[j] + 1)
        own = [w for w, n in c.most_common(4 * LEXICON) if n >= LEXICON_COUNT and all(rate(w, k) > 4 * rate(w, j) for j in range(len(labels)) if j != k)]
        lexicon |= dict.fromkeys(own[:LEXICON], k)
    # Runs of 4 to 12 words; the next run is of the same document four times in five.
    runs: list[list[tuple[list[bytes], int]]] = []
    budget = max(40, most_words // len(tokenised))
    for words, lang in tokenised:
        own, at, taken = [], 0, 0
        while taken < min(len(words), budget):  # a longer text's runs begin anywhere in it
            n = int(rng.integers(4, 13))
            at = int(rng.integers(0, max(1, len(words) - n + 1))) if len(words) > budget else taken
            own.append((words[at : at + n], index[lang]))
            taken += n
        runs.append(own)
    ids, gold, lengths = WordIds(), [], []
    tokens: list[int] = []
    waiting = [i for i in rng.permutation(len(runs)) if runs[i]]
    at = 0
    while waiting:
        at %= len(waiting)
        used = 0
        while waiting and used < 40:
            words, label = runs[waiting[at]].pop(0)
            tokens += [ids[w] for w in words]
            gold += [label] * len(words)
            used += len(words)
            if not runs[waiting[at]]:
                waiting.pop(at)
                at = int(rng.integers(0, max(1, len(waiting))))
            elif rng.random() < 0.2:
                at = int(rng.integers(0, len(waiting)))
            if waiting:
                at %= len(waiting)
        lengths.append(used)
    token, truth, length = np.asarray(tokens), np.asarray(gold), np.asarray(lengths)
    start = np.cumsum(length) - length
    row, col = ngrams(ids.words)
    share = np.sqrt(np.bincount(row, minlength=len(ids.words)))
    known = np.asarray([lexicon.get(w, -1) for w in ids.words])
    hit = np.flatnonzero(known >= 0)
    m, d = len(labels), 1 << BITS
    inner = np.ones(len(token), dtype=bool)
    inner[start] = False
    seen_moves = np.zeros((m, m))
    np.add.at(seen_moves, (truth[np.flatnonzero(inner) - 1], truth[inner]), 1)
    seen_first = np.bincount(truth[start], minlength=m).astype(np.float64)
    f = Field(labels, np.zeros((m, d), np.float32), lexicon, np.zeros((m, m), np.float32), np.zeros((m, m), np.float32), np.zeros(m, np.float32))
    parts = {name: [np.zeros_like(getattr(f, name), dtype=np.float64) for _ in range(2)] for name in ("weights", "in_lexicon", "moves", "first")}
    truth_share = np.eye(m, dtype=np.float32)[:, truth]
    for step in range(1, steps + 1):
        emission = np.stack([np.bincount(row, weights=f.weights[k][col], minlength=len(share)) / share for k in range(m)]).astype(np.float32)
        emission[:, hit] += f.in_lexicon[:, known[hit]]
        p, _, pairs = marginals(emission[:, token], f.moves, f.first, start, length, pairs=True)
        error = p - truth_share
        by_word = np.stack([np.bincount(token, weights=error[k], minlength=len(share)) for k in range(m)]) / len(token)
        grads = {
            "weights": np.stack([np.bincount(col, weights=(by_word[k] / share)[row], minlength=d) for k in range(m)]) + 1e-7 * f.weights,
            "in_lexicon": np.stack([np.bincount(known[hit], weights=by_word[k][hit], minlength=m) for k in range(m)]),
            "moves": (pairs - seen_moves) / len(token), "first": (p[:, start].sum(axis=1) - seen_first) / len(token),
        }
        for name, g in grads.items():
            mean, square = parts[name]
            mean += 0.1 * (g - mean)
            square += 0.01 * (g * g - square)
            getattr(f, name)[...] -= 0.3 * np.sqrt(1 - 0.99**step) / (1 - 0.9**step) * mean / (np.sqrt(square) + 1e-8)
    return f


def label_texts(found: list[bytes | None], f: Field) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best label of each text (-1: none), its mean marginal, and the texts' word counts, for a block of texts."""
    ids = WordIds()
    tokens: list[int] = []
    lengths: list[int] = []
    owners: list[int] = []
    look = ids.__getitem__
    for i, text in enumerate(found):
        for line in text.translate(_LETTERS).split(b"\n") if text else ():
            words = line.split()
            if words:
                tokens += map(look, words)
                lengths.append(len(words))
                owners.append(i)
    clean = [letters(w) for w in ids.words]
    has = np.asarray([bool(w) for w in clean], dtype=bool)
    token = np.asarray(tokens, dtype=np.int64)
    owner = np.repeat(np.asarray(owners, dtype=np.int64), lengths)
    line = np.repeat(np.arange(len(lengths)), lengths)
    real = has[token] if len(token) else np.zeros(0, bool)
    token, owner, line = token[real], owner[real], line[real]
    best, score = np.full(len(found), -1), np.zeros(len(found))
    count = np.bincount(owner, minlength=len(found))
    if not len(token):
        return best, score, count
    # Sequences: runs of words of one line, cut after SPAN words.
    head = np.flatnonzero(np.diff(line, prepend=-1))
    place = np.arange(len(line)) - np.repeat(head, np.diff(np.append(head, len(line))))
    start = np.flatnonzero(place % SPAN == 0)
    length = np.diff(np.append(start, len(line)))
    emission = f.emissions([w or b"-" for w in clean])
    p, _, _ = marginals(emission[:, token], f.moves, f.first, start, length)
    sums = np.stack([np.bincount(owner, weights=p[k], minlength=len(found)) for k in range(len(f.labels))])
    some = count > 0
    best[some] = sums[:, some].argmax(axis=0)
    score[some] = np.clip(sums[best[some], np.flatnonzero(some)] / count[some], 0, 1)
    return best, score, count


def drawn(text: bytes) -> bytes:
    """`DRAWN` words of a text that has more, in runs spread evenly over the whole of it."""
    words = text.translate(_LETTERS).split()
    if len(words) <= DRAWN:
        return b" ".join(words)
    starts = np.linspace(0, len(words) - RUN, DRAWN // RUN).astype(int).tolist()
    return b" ".join(w for at in starts for w in words[at : at + RUN])


def fit(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> Field | None:
    """Learn from `docs` (doc_id, text, lang); the caller leaves the held-out fold out. Rows that repeat a doc_id teach once."""
    able = docs.where("lang IS NOT NULL AND doc_id IS NOT NULL AND text IS NOT NULL")
    counts = {r["lang"]: r["n"] for r in able.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return None
    share = max(1, sample_docs // len(counts))
    chosen = reduce(DataFrame.unionByName, [sampled(able.where(F.col("lang") == lang), F.col("doc_id"), share, n) for lang, n in sorted(counts.items())])
    once = chosen.groupBy("doc_id").agg(F.min(F.struct("lang", "text")).alias("x")).select("doc_id", "x.lang", "x.text")

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in pieces(batches):
            some = pa.array([drawn(t) for t in texts(piece.column("text"))], pa.binary())
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), piece.column("lang"), some], names=["doc_id", "lang", "words"])

    kind = dict(once.dtypes)["doc_id"]
    found = sorted((r["doc_id"], r["lang"], bytes(r["words"])) for r in once.mapInArrow(blocks, f"doc_id {kind}, lang string, words binary").collect())
    return train([(words, lang) for _, lang, words in found])


def identify(docs: DataFrame, f: Field | None) -> DataFrame:
    """doc_id, lang_pred, score, n_words for every row of `docs`."""
    sent = docs.sparkSession.sparkContext.broadcast(f)

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = sent.value
        for piece in pieces(batches, 3_000_000):
            best, score, count = label_texts(texts(piece.column("text")), model) if model else (np.full(piece.num_rows, -1), np.zeros(piece.num_rows), np.zeros(piece.num_rows, np.int64))
            names = [model.labels[k] if k >= 0 else "und" for k in best]
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array(names, pa.string()), pa.array(score), pa.array(count.astype(np.int64))], names=["doc_id", "lang_pred", "score", "n_words"])

    return docs.selectExpr("CAST(doc_id AS BIGINT) AS doc_id", "text").mapInArrow(blocks, "doc_id long, lang_pred string, score double, n_words long")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    found = identify(docs.select("doc_id", "text"), fit(docs.where(~held_out(F.col("doc_id")))))
    return found.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "lang_pred", "score", "n_words")
