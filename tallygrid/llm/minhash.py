"""Near-duplicate documents by circulant MinHash.

Signatures need two permutations of the 32-bit numbers: the first shuffles a set once, the second is applied to the shuffled set
moved on by 0, 1, 2, ... places, and the least value after each move is one coordinate. Coordinates are cut into bands; sets that
share a band are candidates, and every link is confirmed on the full sets.

Equal sets are one class from the start. Candidates are joined to the least class of their band bucket only, so no bucket is expanded into
pairs. The components of these joins hold all candidates of all their members; each is checked by itself with an index from shingles to
sets, and the check passes over one set at a time until all sets that weren't passed lie in one true component: then no link
between two components can be left. Unlike texts that share boilerplate can chain into a component of more than `group_shingles`; there only sets
that share a bucket are compared, bucket by bucket, and buckets of the same sets once. A bucket that is larger still is cut into parts, and
each pair of parts is checked in a task of its own.

Defined results: texts that are null or without words have n_shingles 0, are linked with nothing and are kept; a text of fewer than five
words is one shingle; rows that repeat a doc_id have the same component; rows without doc_id join no component (component_id null, kept
false); an empty table gives an empty result. Only doc_id and text are read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import LOWER, WordHashes, cut, join_by_key, pieces, table, texts
from .graph import components

WORDS, PERCENT, BANDS, ROWS = 5, 75, 32, 5
GROUP_SHINGLES = 2_000_000
SIGNATURES = "doc_id long, n_shingles long, hi long, lo long, bands array<long>"
#: Odd multipliers of public 32- and 64-bit finishers.
_M1, _M2, _M3, _M4 = np.uint32(0x85EBCA6B), np.uint32(0xC2B2AE35), np.uint32(0x7FEB352D), np.uint32(0x846CA68B)
_L1, _L2 = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0x9E3779B97F4A7C15)


def _mixed(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(33))
    x = x * _L1
    return x ^ (x >> np.uint64(29))


def shingle_sets(found: list[bytes | None], hashes: WordHashes) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingles of each text."""
    look = hashes.__getitem__
    sets = []
    for text in found:
        words = text.translate(LOWER).split() if text else []
        if not words:
            sets.append(np.empty(0, dtype=np.uint64))
            continue
        w = np.fromiter(map(look, words), dtype=np.uint64, count=len(words))
        span = min(WORDS, len(w))
        total = np.full(len(w) - span + 1, span, dtype=np.uint64)
        for k in range(span):
            total = _mixed(total * _L2 + w[k : len(w) - span + 1 + k])
        sets.append(np.unique(total))
    return sets


def _first(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint32(16))
    x *= _M3
    x ^= x >> np.uint32(15)
    x *= _M4
    return x ^ (x >> np.uint32(16))


def _second(x: np.ndarray, spare: np.ndarray) -> np.ndarray:
    """In place."""
    for shift, by in ((16, _M1), (13, _M2)):
        np.right_shift(x, np.uint32(shift), out=spare)
        np.bitwise_xor(x, spare, out=x)
        np.multiply(x, by, out=x)
    np.right_shift(x, np.uint32(16), out=spare)
    return np.bitwise_xor(x, spare, out=x)


def signatures(sets: list[np.ndarray], coordinates: int, block: int = 32_768) -> np.ndarray:
    """uint32 matrix, sets by coordinates; the sets aren't empty."""
    out = np.empty((len(sets), coordinates), dtype=np.uint32)
    at = 0
    while at < len(sets):
        to, total = at, 0
        while to < len(sets) and (to == at or total + len(sets[to]) <= block):
            total += len(sets[to])
            to += 1
        sizes = np.asarray([len(s) for s in sets[at:to]])
        starts = np.cumsum(sizes) - sizes
        base = _first(np.concatenate(sets[at:to]).astype(np.uint32))
        x, spare = np.empty_like(base), np.empty_like(base)
        for k in range(coordinates):
            np.add(base, np.uint32(k), out=x)  # one place further round the circle
            out[at:to, k] = np.minimum.reduceat(_second(x, spare), starts)
        at = to
    return out


def band_keys(signature: np.ndarray, bands: int, rows: int) -> np.ndarray:
    parts = signature.reshape(len(signature), bands, rows).astype(np.uint64)
    key = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64) * _L2, (len(signature), bands)).copy()
    for r in range(rows):
        key = _mixed(key * _L2 + parts[:, :, r])
    return key.view(np.int64)


def _set_key(s: np.ndarray) -> tuple[int, int]:
    digest = xxhash.xxh3_128_digest(s.tobytes())
    return int.from_bytes(digest[:8], "little", signed=True), int.from_bytes(digest[8:], "little", signed=True)


def sign(docs: DataFrame, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """Rows of SIGNATURES; bands is null for empty sets."""

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for piece in pieces(batches, 3_000_000):
            sets = shingle_sets(texts(piece.column("text")), hashes)
            full = [i for i, s in enumerate(sets) if len(s)]
            keys = band_keys(signatures([sets[i] for i in full], bands * rows), bands, rows) if full else np.empty((0, bands), np.int64)
            counts = np.zeros(len(sets) + 1, dtype=np.int32)
            counts[np.asarray(full, dtype=np.int64) + 1] = bands
            has = np.zeros(len(sets), dtype=bool)
            has[full] = True
            ids = [_set_key(s) for s in sets]
            lists = pa.ListArray.from_arrays(pa.array(np.cumsum(counts), pa.int32()), pa.array(keys.ravel()), mask=pa.array(~has))
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()), pa.array([i[0] for i in ids], pa.int64()), pa.array([i[1] for i in ids], pa.int64()), lists], names=["doc_id", "n_shingles", "hi", "lo", "bands"])

    return docs.selectExpr("CAST(doc_id AS BIGINT) AS doc_id", "text").mapInArrow(blocks, SIGNATURES)


def true_roots(sets: list[np.ndarray], percent: int = PERCENT) -> np.ndarray:
    """For each set, the least index in its component of links with 100 * common >= percent * united."""
    m = len(sets)
    parent = np.arange(m)
    if m < 2:
        return parent
    size = np.asarray([len(s) for s in sets])
    _, ids = np.unique(np.concatenate(sets), return_inverse=True)
    owner = np.repeat(np.arange(m), size)
    order = np.argsort(ids, kind="stable")
    holders, count = owner[order], np.bincount(ids)
    start = np.cumsum(count) - count
    end = np.cumsum(size)
    shared = count[ids]
    passed = np.zeros(m, dtype=bool)
    weight = np.bincount(owner, weights=shared, minlength=m)
    ranked = np.argsort(-weight, kind="stable")
    pick = int(ranked[0])
    while pick >= 0:
        own = ids[end[pick] - size[pick] : end[pick]]
        own = own[count[own] > 1]
        lengths = count[own]
        at = np.repeat(start[own] - (np.cumsum(lengths) - lengths), lengths) + np.arange(lengths.sum())
        common = np.bincount(holders[at], minlength=m)
        hit = np.flatnonzero((100 * common >= percent * (size + size[pick] - common)) & (common > 0))
        passed[pick] = True
        roots = np.unique(np.append(parent[hit], parent[pick]))
        if len(roots) > 1:
            parent[np.isin(parent, roots)] = roots[0]
        largest = np.bincount(parent, minlength=m).argmax()
        rest = ranked[~passed[ranked] & (parent[ranked] != largest)]
        pick = int(rest[0]) if len(rest) else -1
    return parent


def _check(group: pa.Table) -> pa.Table:
    """(node, root) of the true components inside each candidate component of the group."""
    group = group.sort_by([("part", "ascending"), ("node", "ascending")])
    sets = shingle_sets(texts(group.column("text").combine_chunks()), WordHashes())
    part, node = group.column("part").to_numpy(), group.column("node").to_numpy()
    kept = np.asarray([_set_key(s) == k for s, k in zip(sets, zip(group.column("hi").to_pylist(), group.column("lo").to_pylist(), strict=True), strict=True)], dtype=bool)
    kept[1:] &= ~((part[1:] == part[:-1]) & (node[1:] == node[:-1]) & kept[:-1])  # repeated rows
    at = np.flatnonzero(kept)
    roots = node.copy()
    edges = np.flatnonzero(np.diff(part[at], prepend=part[at][:1] - 1)) if len(at) else []
    for a, b in zip(edges, [*edges[1:], len(at)], strict=True):
        own = at[a:b]
        roots[own] = node[own][true_roots([sets[i] for i in own])]
    return pa.table({"node": node[at], "root": roots[at]})


def _by_bucket(members: DataFrame, buckets: DataFrame, group_shingles: int) -> DataFrame:
    """(doc_id, node, hi, lo, part, bin): the groups in which members of large components are compared, one for each bucket and pair of its parts."""
    held = cut(buckets.join(members, "node"))
    sizes = held.groupBy("key").agg(F.sum("n_shingles").alias("weight"), F.count("*").alias("n"), F.sum(F.xxhash64("node").cast("decimal(38,0)")).alias("same"))
    once = sizes.where("n > 1").groupBy("n", "same", "weight").agg(F.min("key").alias("key")).select("key", "n", F.ceil(F.col("weight") / group_shingles).cast("int").alias("parts"))
    own = join_by_key(held, once, ["key"], "n", held.count()).withColumn("own", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    own = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    part = F.xxhash64("key", F.least("own", "other"), F.greatest("own", "other"))
    return own.select("doc_id", "node", "hi", "lo", part.alias("part"), part.alias("bin"))


def near_duplicates(docs: DataFrame, bands: int = BANDS, rows: int = ROWS, group_shingles: int = GROUP_SHINGLES) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of `docs`."""
    signed = cut(sign(docs, bands, rows))
    real = signed.where("n_shingles > 0 AND doc_id IS NOT NULL")
    classes = real.groupBy("hi", "lo").agg(F.min("doc_id").alias("doc_id"), F.first("n_shingles").alias("n_shingles"), F.first("bands").alias("bands"))
    classes = cut(classes.withColumn("node", F.monotonically_increasing_id()))
    buckets = classes.select("node", F.explode("bands").alias("key"))
    heads = buckets.groupBy("key").agg(F.min("node").alias("head"), F.count("*").alias("n")).where("n > 1")
    hung = join_by_key(buckets, heads, ["key"], "n", bands * classes.count())
    closure = cut(components(hung.where("node <> head").select(F.col("node").alias("a"), F.col("head").alias("b"))))

    members = cut(classes.drop("bands").join(closure, "node"))
    weights = members.groupBy("root").agg(F.sum("n_shingles").alias("weight"), F.count("*").alias("n"))
    members = cut(join_by_key(members, weights, ["root"], "n", members.count()).select("node", "hi", "lo", "doc_id", "root", "n_shingles", "weight"))
    weight, most = members.agg(F.coalesce(F.sum("n_shingles"), F.lit(0)), F.coalesce(F.max("weight"), F.lit(0))).first()
    bins = int(max(1, -(-weight // group_shingles)))
    # A small component goes to a bin with others; of a large one, each bucket is a group, or each pair of a bucket's parts.
    placed = members.where(F.col("weight") <= group_shingles).select("doc_id", "node", "hi", "lo", F.col("root").alias("part"), F.pmod(F.xxhash64("root"), F.lit(bins)).alias("bin"))
    if most > group_shingles:
        large = members.where(F.col("weight") > group_shingles).select("node", "hi", "lo", "doc_id", "n_shingles")
        placed = placed.unionByName(_by_bucket(large, buckets, group_shingles))
    named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(placed.select("doc_id", "node", "hi", "lo", "part", "bin"), "doc_id")
    links = cut(named.select("bin", "part", "node", "hi", "lo", "text").groupBy("bin").applyInArrow(_check, "node long, root long"))
    if most > group_shingles:
        links = components(links.select(F.col("node").alias("a"), F.col("root").alias("b")))
    roots = cut(links.join(classes.select("node", "doc_id"), "node"))
    least = roots.groupBy("root").agg(F.min("doc_id").alias("component_id"), F.count("*").alias("n"))
    named_roots = join_by_key(roots.select("node", "root"), least, ["root"], "n", roots.count())
    by_class = classes.select("hi", "lo", "node", F.col("doc_id").alias("first_id")).join(named_roots, "node", "left").select("hi", "lo", F.least(F.coalesce("component_id", "first_id"), "first_id").alias("component_id"))
    alone = F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id"))
    found = signed.drop("bands").join(by_class, ["hi", "lo"], "left").withColumn("component_id", F.when(F.col("doc_id").isNotNull(), alone))
    return found.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False)).alias("kept"))


def deduplicate(docs: DataFrame) -> DataFrame:
    """`docs`, all columns, without the documents that another one stands for."""
    dropped = near_duplicates(docs).where("NOT kept AND doc_id IS NOT NULL").select(F.col("doc_id").alias("__dropped")).distinct()
    return docs.join(dropped, F.col("doc_id").cast("long") == F.col("__dropped"), "left_anti")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))
