"""Best-fit packing: a document goes to the open sequence that its size vector suits best, under every capacity.

Sizes have three parts: tokens, documents, and attention cost (length squared). Among the sequences in which all three fit, the one with
the smallest weighted norm of what would be left is taken (`choice="norm"`), or the one with the largest weighted dot product of need and what is left
(`choice="dot"`). All three residuals weigh alike by default, so of two sequences with the same room for tokens the one with fewer documents and less attention cost left is filled
first; tests hold the number of sequences against that of plain best fit and the least that the tokens allow. Longest pieces come first. Documents longer than
a sequence are cut into whole sequences; what is over is their first piece.

Texts never leave the task that reads them: tokenizing gives a row of numbers per piece. A piece that fills a sequence is one at once; the others are dealt by hash
to groups of about `group_rows` pieces, each packed by itself. A group leaves few open sequences behind, so the waste doesn't grow.

Token ids are those of the tokenizer file. Texts of plain Latin letters go through a faster coder with the same ranks (tests hold
the two against each other); all others, and texts that hold a special token's string, go through the tokenizer itself.

Defined results: a null or empty text is its end mark alone, one token; repeated rows are packed as separate documents; rows without doc_id are
packed too; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import math
import re
import zlib
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.shared import keep
from .common import pieces, table, texts

LENGTH, END, GROUP_ROWS = 1024, 2, 20_000
SEQUENCE_STRIDE = 1 << 32
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
#: Characters for which both coders split words alike: ASCII without rare controls, Latin letters and signs.
_PLAIN = re.compile("[^\t\n\r\x20-\x7e -ɏ]")


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Coder:
    """Token ids of texts, as a uint32 array each."""

    def __init__(self, path: str, ranks: str | None, pattern: str | None):
        from tokenizers import Tokenizer

        self.exact = Tokenizer.from_file(path)
        self.special = [t.content for t in self.exact.get_added_tokens_decoder().values()]
        self.fast = None
        if ranks:
            import tiktoken

            with open(ranks, "rb") as lines:
                merges = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
            self.fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=merges, special_tokens={})

    def ids(self, text: str) -> np.ndarray:
        if self.fast is None or _PLAIN.search(text) or any(s in text for s in self.special):
            return np.asarray(self.exact.encode(text, add_special_tokens=False).ids, dtype=np.uint32)
        return np.asarray(self.fast.encode_ordinary(text), dtype=np.uint32)


@lru_cache(maxsize=2)
def coder(path: str, ranks: str | None, pattern: str | None) -> Coder:
    return Coder(path, ranks, pattern)


def token_pieces(docs: DataFrame, path: str, ranks: str | None, pattern: str | None, length: int, end: int) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every piece; ids as little-endian unsigned 32-bit numbers."""

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code = coder(path, ranks, pattern)
        for part in pieces(batches):
            rows: list[tuple] = []
            for doc_id, text in zip(part.column("doc_id").to_pylist(), texts(part.column("text")), strict=True):
                ids = np.append(code.ids(text.decode()) if text else np.empty(0, np.uint32), np.uint32(end)).astype("<u4")
                first = len(ids) % length or length
                edges = [0, *range(first, len(ids) + 1, length)]
                rows += [(doc_id, k, a, b - a, zlib.crc32(ids[a:b].tobytes())) for k, (a, b) in enumerate(zip(edges, edges[1:], strict=False))]
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    return docs.selectExpr("CAST(doc_id AS BIGINT) AS doc_id", "text").mapInArrow(blocks, "doc_id long, piece int, start long, length long, ids_crc32 long")


def vector_best_fit(lengths: np.ndarray, capacity: tuple[int, int, int], weights: tuple[float, float, float] = (1.0, 1.0, 1.0), choice: str = "norm") -> tuple[np.ndarray, np.ndarray]:
    """(bin, offset) of each length, in the order given; lengths come in falling order for the best fit.

    Bins in the same state are alike, so they are kept as stacks by state: the search goes over distinct residual vectors, which are rows of one array.
    """
    full, weight = np.asarray(capacity, dtype=np.float64), np.asarray(weights, dtype=np.float64)
    bins, offsets = np.empty(len(lengths), dtype=np.int64), np.empty(len(lengths), dtype=np.int64)
    room, at_state, stacks, made = np.empty((256, 3), dtype=np.int64), {}, [], 0
    for i, size in enumerate(lengths.tolist()):
        need = (size, 1, size * size)
        if need[0] > capacity[0] or need[2] > capacity[2]:
            raise ValueError(f"a piece of {size} tokens fits into no sequence")
        at = np.flatnonzero((room[: len(stacks)] >= need).all(axis=1))
        if len(at):
            left, ask = room[at] / full, np.asarray(need) / full
            score = -(left * ask) @ weight if choice == "dot" else (left - ask) ** 2 @ weight
            pick = int(at[np.argmin(score)])
            state, number = tuple(room[pick].tolist()), stacks[pick].pop()
            if not stacks[pick]:  # the last state takes the place of one without bins
                del at_state[state]
                last = stacks.pop()
                if pick < len(stacks):
                    stacks[pick], room[pick] = last, room[len(stacks)]
                    at_state[tuple(room[pick].tolist())] = pick
        else:
            state, number, made = tuple(capacity), made, made + 1
        bins[i], offsets[i] = number, capacity[0] - state[0]
        after = (state[0] - need[0], state[1] - need[1], state[2] - need[2])
        if min(after) > 0:
            if after not in at_state:
                if len(stacks) == len(room):
                    room = np.concatenate([room, np.empty_like(room)])
                room[len(stacks)], at_state[after] = after, len(stacks)
                stacks.append([])
            stacks[at_state[after]].append(number)
    return bins, offsets


def pack(docs: DataFrame, path: str, ranks: str | None = None, pattern: str | None = None, length: int = LENGTH, end: int = END, most_documents: int | None = None, most_attention: int | None = None, weights: tuple[float, float, float] = (1.0, 1.0, 1.0), choice: str = "norm", group_rows: int = GROUP_ROWS) -> DataFrame:
    """Rows of PIECES for every document of `docs`. Without own limits, documents and attention cost are bounded by `length` and its square."""
    capacity = (length, most_documents or length, most_attention or length * length)
    longest = min(length, math.isqrt(capacity[2]))  # a piece must fit into a sequence of its own
    # A document has one piece that isn't whole; where no piece may be whole, as many as its bytes, of which a token has one at least.
    loose = F.count("*") if longest == length else F.sum(F.ceil((F.coalesce(F.octet_length("text"), F.lit(0)) + 1) / longest))
    groups = max(1, -(-int(docs.agg(loose).first()[0] or 0) // group_rows))
    cut = token_pieces(docs, path, ranks, pattern, longest, end)
    whole = F.col("length") == length
    # A group is known by its hash alone; ties of doc_id are told apart by content, so copies of a row spread no further than they must.
    # What is in no group gets a number below 0, unlike those of groups.
    alone = F.struct((-1 - F.monotonically_increasing_id()).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    keyed = keep(cut.withColumn("alone", F.when(whole, alone)), "pieces")
    dealt = keyed.where("alone IS NULL").drop("alone").withColumn("__group", F.pmod(F.xxhash64(F.lit("pack"), "doc_id", "piece", "ids_crc32"), F.lit(groups)).cast("int"))

    def packed(key: tuple, part: pa.Table) -> pa.Table:
        number = lambda name: pc.fill_null(part.column(name), -1).to_numpy()
        order = np.lexsort((number("ids_crc32"), number("piece"), number("doc_id"), -number("length")))
        part = part.drop_columns("__group").take(pa.array(order))
        bins, offsets = vector_best_fit(part.column("length").to_numpy(), capacity, weights, choice)
        return part.append_column("sequence_id", pa.array(key[0].as_py() * SEQUENCE_STRIDE + bins)).append_column("offset", pa.array(offsets))

    names = [c.split()[0] for c in PIECES.split(", ")]
    filled = keyed.where("alone IS NOT NULL").select(*names[:5], "alone.sequence_id", "alone.offset")
    return dealt.groupBy("__group").applyInArrow(packed, PIECES).unionByName(filled)


def packed_documents(docs: DataFrame) -> DataFrame:
    import public_tokenizers

    return pack(docs, tokenizer_path("byte_bpe_50k.json"), tokenizer_path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed_documents(table(spark, sf_dir, "documents", "doc_id", "text"))
