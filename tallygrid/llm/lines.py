"""Line dedup by a deletion-neighbourhood join: lines that differ by one word at most from an earlier line go.

A line is a \\n-split part; it is compared as its sequence of words. A line of `least_words` or more is dropped if an earlier line (smaller
doc_id, then smaller line number) has the same words, or, from `near_words` words on, if one word inserted, deleted or replaced
makes them equal. Earlier lines count whether they stay or not. Both floors are 1 unless given: all lines with a word are judged,
and as one edit turns any word into any other, all lines of one word but the first go.

Two lines within one edit share a variant: both lose the word at the same place (replacement), or one loses a word and the
other none (insertion). Variants are hashed keys. Replacement keys carry the place, so that all lines under one key are within the
bound of each other, and an insertion key has one whole line. The earliest line under a key therefore stands for
all others: links are formed from each line to it alone, never between all pairs. Found links are verified on the words.

One edit leaves the first or the second half of a line as it was. So before variants are made, halves are counted, and a line makes
variants only for the half that may differ, and only if another line shares its other half. A variant's hash is a polynomial in the words' hashes, so it is
put together from the hashes of what stands before and behind the lost word: the work of a line is proportional to its words.

Defined results: null, empty and blank texts have no lines; blank lines are never dropped; rows that repeat a doc_id are one
document, and the same line of it at the same place is one line; rows without doc_id take no part and are handed on unchanged; an empty table gives an
empty result. Only doc_id and text are read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WordHashes, cut, pieces, table, texts

LEAST_WORDS, NEAR_WORDS = 1, 1
_hash = xxhash.xxh3_64_intdigest
#: An odd base of the polynomial, and its inverse, modulo 2^64.
_BASE = 0x9E3779B97F4A7C15
_INVERSE = np.uint64(pow(_BASE, -1, 1 << 64))


def _signed(value: int) -> int:
    return value - (1 << 64) if value >> 63 else value


def _halves(words: list[bytes]) -> list[tuple[int, int]]:
    """(key, side): the ends of a line that one edit elsewhere leaves alone, at each length that a partner may have."""
    found = []
    for n in {len(words) // 2, (len(words) - 1) // 2} - {0}:
        found += [(_signed(_hash(b" ".join(words[:n]), n)), 0), (_signed(_hash(b" ".join(words[-n:]), n + (1 << 32))), 1)]
    return found


def _scan(docs: DataFrame, make, schema: str) -> DataFrame:
    """make(doc_id, line, words) -> rows, for all lines with a word."""

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in pieces(batches):
            rows: list[tuple] = []
            for doc_id, text in zip(piece.column("doc_id").to_pylist(), texts(piece.column("text")), strict=True):
                for line, raw in enumerate(text.split(b"\n")) if text else ():
                    if words := raw.split():
                        rows += make(doc_id, line, words)
            if rows:
                yield _block(schema, rows)

    return docs.where("doc_id IS NOT NULL").selectExpr("CAST(doc_id AS BIGINT) AS doc_id", "text").mapInArrow(blocks, schema)


_KINDS = {"long": pa.int64(), "int": pa.int32(), "string": pa.string()}


def _arrow(schema: str) -> pa.Schema:
    return pa.schema([(n, _KINDS[k]) for n, k in (c.split() for c in schema.split(", "))])


def _block(schema: str, rows: list[tuple]) -> pa.RecordBatch:
    kinds = _arrow(schema)
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), kinds, strict=True)], schema=kinds)


def scan_lines(docs: DataFrame, least_words: int = LEAST_WORDS, near_words: int = NEAR_WORDS) -> DataFrame:
    """(doc_id, line, h, k0 .. k3): h is the hash of the words, null for lines too short to be judged; k0 to k3 are the keys of its halves, k0 null
    for lines too short to be near another. A line of one or two words may share an empty half, which any line has: k3 alone, without k2, marks it."""

    def make(doc_id: int, line: int, words: list[bytes]) -> list[tuple]:
        n = len(words)
        h = _signed(_hash(b" ".join(words))) if n >= min(least_words, near_words - 1) else None
        keys: list[int | None] = [k for k, _ in _halves(words)] if n >= near_words - 1 else []
        keys += [None] * (4 - len(keys))
        if near_words - 1 <= n <= 2:
            keys[0], keys[3] = h if keys[0] is None else keys[0], 0
        return [(doc_id, line, h, *keys)]

    return _scan(docs, make, "doc_id long, line int, h long, k0 long, k1 long, k2 long, k3 long")


def candidates(scanned: DataFrame) -> DataFrame:
    """(doc_id, line, first, second): earliest copies of lines that share a half with another line; first: the first half may differ."""
    distinct = scanned.where("k0 IS NOT NULL").groupBy("h").agg(F.min(F.struct("doc_id", "line", "k0", "k1", "k2", "k3")).alias("x")).select("x.*")
    sides = F.array("k0", "k1", "k2", F.when(F.col("k2").isNotNull(), F.col("k3")))
    halves = distinct.select("doc_id", "line", F.posexplode(sides).alias("side", "key")).where("key IS NOT NULL").withColumn("side", F.col("side") % 2)
    shared = halves.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key")
    tiny = distinct.where("k2 IS NULL AND k3 IS NOT NULL").select("doc_id", "line", F.explode(F.array(F.lit(0), F.lit(1))).alias("side"))
    return halves.join(shared, "key").select("doc_id", "line", "side").unionByName(tiny).groupBy("doc_id", "line").agg(F.max(F.col("side") == 1).alias("first"), F.max(F.col("side") == 0).alias("second"))


def _finished(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    return (x ^ (x >> np.uint64(29))).view(np.int64)


def variant_keys(words: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Keys of whole lines, and of each line without each of its words; `words`: hashes of all lines' words, one line after the other."""
    end = np.cumsum(size)
    start = end - size
    place = np.arange(len(words)) - np.repeat(start, size)
    powers = np.ones(int(size.max(initial=1)), dtype=np.uint64)
    powers[1:] = np.cumprod(np.full(len(powers) - 1, _BASE, dtype=np.uint64))
    until = np.concatenate([np.zeros(1, np.uint64), np.cumsum(words * powers[place], dtype=np.uint64)])
    before = until[:-1] - np.repeat(until[start], size)
    behind = np.repeat(until[end], size) - until[1:]
    return _finished(until[end] - until[start]), _finished(before + behind * _INVERSE)


def _variants(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, place, doc_id, line): keys of a line without the word at `place`, and at place -1 of the whole line."""
    look = WordHashes().__getitem__
    for piece in pieces(batches, 1_000_000):
        found = [text.split(b" ") for text in texts(piece.column("text"))]
        size = np.asarray([len(w) for w in found], dtype=np.int64)
        hashes = np.fromiter((look(w) for line in found for w in line), dtype=np.uint64, count=int(size.sum()))
        first, second = (np.asarray(piece.column(c).to_pylist(), dtype=bool) for c in ("first", "second"))
        whole, less = variant_keys(hashes, size)
        place = np.arange(len(hashes)) - np.repeat(np.cumsum(size) - size, size)
        low, high = np.where(first, 0, np.maximum(0, size // 2 - 1)), np.where(second, size, np.minimum(size, size // 2 + 1))
        at = np.flatnonzero((place >= np.repeat(low, size)) & (place < np.repeat(high, size)))
        owner = np.concatenate([np.arange(len(size)), np.repeat(np.arange(len(size)), size)[at]])
        key, spot = np.concatenate([whole, less[at]]), np.concatenate([np.full(len(size), -1), place[at]]).astype(np.int32)
        yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(spot), piece.column("doc_id").take(pa.array(owner)), piece.column("line").take(pa.array(owner))], names=["key", "place", "doc_id", "line"])


def within_one(a: list[bytes], b: list[bytes]) -> bool:
    """Is one word inserted, deleted or replaced, or nothing, enough to make `a` into `b`?"""
    if len(a) > len(b):
        a, b = b, a
    if len(b) - len(a) > 1:
        return False
    p = next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), len(a))
    return a[p + 1 :] == b[p + 1 :] if len(a) == len(b) else a[p:] == b[p + 1 :]


def _verified(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for piece in batches:
        fits = [within_one(a.split(b" "), b.split(b" ")) for a, b in zip(texts(piece.column("text")), texts(piece.column("partner")), strict=True)]
        yield piece.select(["doc_id", "line"]).filter(pa.array(fits, pa.bool_()))


def near_lines(docs: DataFrame, scanned: DataFrame, near_words: int = NEAR_WORDS) -> DataFrame:
    """(doc_id, line) of earliest copies of lines that have an earlier line within one edit."""
    found = cut(candidates(scanned))

    def make(doc_id: int, line: int, words: list[bytes]) -> list[tuple]:
        return [(doc_id, line, b" ".join(words).decode())] if len(words) >= near_words - 1 else []

    with_text = cut(_scan(docs, make, "doc_id long, line int, text string").join(found, ["doc_id", "line"]).dropDuplicates(["doc_id", "line"]))
    keys = with_text.mapInArrow(_variants, "key long, place int, doc_id long, line int").withColumn("at", F.struct("doc_id", "line"))
    by_place = keys.groupBy("key", "place").agg(F.min("at").alias("earliest"), F.count("*").alias("n"))
    over = Window.partitionBy("key")
    whole = F.min(F.when(F.col("place") < 0, F.col("earliest"))).over(over)
    parts = F.min(F.when(F.col("place") >= 0, F.col("earliest"))).over(over)
    by_place = by_place.withColumn("whole", whole).withColumn("parts", parts).withColumn("all", F.sum("n").over(over)).where("all > 1")
    joined = keys.join(by_place.select("key", "place", "earliest", "whole", "parts"), ["key", "place"])
    partner = F.when(F.col("place") < 0, F.col("parts")).otherwise(F.least("earliest", F.coalesce("whole", "earliest")))
    pairs = joined.withColumn("partner", partner).where("partner < at").select("doc_id", "line", "partner").distinct()
    mine = pairs.join(with_text.select("doc_id", "line", "text"), ["doc_id", "line"])
    theirs = with_text.select(F.col("doc_id").alias("p_doc"), F.col("line").alias("p_line"), F.col("text").alias("partner_text"))
    both = mine.join(theirs, (F.col("partner.doc_id") == F.col("p_doc")) & (F.col("partner.line") == F.col("p_line"))).select("doc_id", "line", "text", F.col("partner_text").alias("partner"))
    long_enough = F.size(F.split("text", " ")) >= near_words
    return both.where(long_enough | (F.size(F.split("partner", " ")) >= near_words)).mapInArrow(_verified, "doc_id long, line int").distinct()


def judge(docs: DataFrame, least_words: int = LEAST_WORDS, near_words: int = NEAR_WORDS) -> DataFrame:
    """doc_id, n_lines, n_exact, n_near and dropped, the numbers from 0 of the document's lines that go, in order."""
    scanned = cut(scan_lines(docs, least_words, near_words))
    near = cut(near_lines(docs, scanned, near_words)).withColumn("is_near", F.lit(True))
    lines = scanned.select("doc_id", "line", "h")
    first = lines.where("h IS NOT NULL").groupBy("h").agg(F.min(F.struct("doc_id", "line")).alias("first"))
    first = first.join(near, (F.col("first.doc_id") == F.col("doc_id")) & (F.col("first.line") == F.col("line")), "left").select("h", "first", F.coalesce("is_near", F.lit(False)).alias("is_near"))
    judged = lines.join(first, "h", "left").withColumn("exact", F.col("first") < F.struct("doc_id", "line"))
    gone = F.coalesce(F.col("exact") | F.col("is_near"), F.lit(False))
    by_doc = judged.groupBy("doc_id").agg(F.countDistinct("line").alias("n_lines"), F.sort_array(F.collect_set(F.when(gone, F.col("line")))).alias("dropped"), F.array_size(F.collect_set(F.when(F.col("exact"), F.col("line")))).cast("long").alias("n_exact"))
    ids = docs.where("doc_id IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id")).distinct()
    none = F.array().cast("array<int>")
    whole = ids.join(by_doc, "doc_id", "left").withColumn("dropped", F.coalesce("dropped", none))
    n = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long")
    return whole.select("doc_id", n("n_lines").alias("n_lines"), n("n_exact").alias("n_exact"), (F.size("dropped") - n("n_exact")).cast("long").alias("n_near"), "dropped")


def deduplicate(docs: DataFrame, least_words: int = LEAST_WORDS, near_words: int = NEAR_WORDS) -> DataFrame:
    """`docs`, all columns, without dropped lines, a column n_chars following the text; a document that loses all its lines with words goes.

    With `least_words` 1 a later exact copy of a document goes whatever the length of its lines; a higher floor leaves it as a stub of its short lines. Further columns may have any
    name, and are handed on as they are.
    """
    verdicts = judge(docs.select("doc_id", "text"), least_words, near_words).where(F.size("dropped") > 0).select(F.col("doc_id").alias("__id"), "dropped", "n_lines")
    rows = docs.select(F.struct("*").alias("__row"))
    joined = rows.join(verdicts, F.col("__row.doc_id").cast("long") == F.col("__id"), "left").where(F.col("dropped").isNull() | (F.size("dropped") < F.col("n_lines")))
    kept = F.array_join(F.filter(F.split("__row.text", "\n", -1), lambda x, i: ~F.array_contains(F.col("dropped"), i)), "\n")
    text = F.when(F.col("dropped").isNull(), F.col("__row.text")).otherwise(kept)
    out = [F.col(f"__row.`{c}`").alias(c) if c not in ("text", "n_chars") else text.alias(c) if c == "text" else F.when(F.col("dropped").isNull(), F.col("__row.n_chars")).otherwise(F.length(kept).cast(docs.schema[c].dataType)).alias(c) for c in docs.columns]
    return joined.select(*out)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents", "doc_id", "text"))
