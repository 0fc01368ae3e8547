"""Best-fit packing of token pieces into sequences by exact complements.

Texts become pieces of at most ``size`` tokens; only longer documents are cut, so that all pieces but
the first have exactly ``size``. What follows works on the histogram of piece lengths, at most
``size`` counts whatever the corpus. From the longest length down, the gap it leaves is filled
exactly by one length, else by a pair, else by a triple that sums to it, looked up under the counts
still available and consumed as often as they allow; the residue is filled best-fit. The result is a
list of patterns (lengths and how often); each holds rank ranges per length. A piece's rank among its
length comes from counts per (length, salt) and a window within each, and finds its slot by a
broadcast join with the patterns, whose number the histogram bounds. Pieces of ``size`` tokens, most of
a corpus of long documents, need no rank: each is a sequence of its own, with a negative number.

Defined results: null text is an empty document of one token, the end id; rows that repeat a doc_id
or have a null one are documents of their own. An empty table gives no rows.
"""

from __future__ import annotations

import base64
import json
import re
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from rippletide.llm.scratch import stored
from rippletide.llm.textbytes import list_column

END_ID = 2
SALTS = 64
LONG_RUN = 100_000
SPACES = re.compile(r"(?<!\s)\s{%d}" % LONG_RUN)
PIECES = "doc_id long, piece int, start long, length int, ids_crc32 long, salt int"


def encoder(path: str) -> Callable[[str], list[int]]:
    """Text to the ids that the tokenizers library gives with the JSON file beside the given rank file, at its
    defaults and without template tokens. tiktoken makes the same ids several times faster (tested), except
    where the text holds an added token, which it would spell out, and in runs of about a million spaces,
    where its pattern overflows; such texts go through the library itself."""
    full = path.removesuffix(".tiktoken") + ".json"
    with open(path, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    with open(full, encoding="utf-8") as f:
        added = re.compile("|".join(re.escape(t["content"]) for t in json.load(f)["added_tokens"]) or r"(?!)")
    fast = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
    whole: list[Tokenizer] = []

    def encode(text: str) -> list[int]:
        if not added.search(text) and (len(text) < LONG_RUN or not SPACES.search(text)):
            return fast(text)
        if not whole:
            whole.append(Tokenizer.from_file(full))
        return whole[0].encode(text, add_special_tokens=False).ids

    return encode


def _encoded(batches: Iterator[pa.RecordBatch], path: str, size: int, with_ids: bool) -> Iterator[pa.RecordBatch]:
    encode = encoder(path)
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            some = batch.slice(at, 256)
            ids = some.column(0).to_pylist()
            doc, piece, start, length, crc, salt, tokens = [], [], [], [], [], [], []
            for d, t in zip(ids, some.column(1).to_pylist(), strict=True):
                seq = np.array(encode(t or "") + [END_ID], "<u4")
                cuts = [0, *range(len(seq) % size or size, len(seq) + 1, size)]
                for n, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
                    c = zlib.crc32(seq[a:b].tobytes())
                    for column, v in ((doc, d), (piece, n), (start, a), (length, b - a), (crc, c), (salt, (c ^ (d or 0) * 2654435761 ^ n * 40503) % SALTS)):
                        column.append(v)
                    if with_ids:
                        tokens.append(seq[a:b])
            arrays = [pa.array(doc, pa.int64()), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int32()), pa.array(crc, pa.int64()), pa.array(salt, pa.int32())]
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "salt"]
            if with_ids:
                arrays.append(list_column(np.concatenate(tokens).astype(np.int64) if tokens else np.zeros(0, np.int64), [len(t) for t in tokens]))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(arrays, names=names)


def plan_patterns(counts: np.ndarray, size: int) -> list[tuple[list[int], int]]:
    """``counts[n]`` pieces of n tokens to (lengths, times) patterns that use each piece once."""
    left = counts.astype(np.int64).copy()
    left[0] = 0
    patterns: list[tuple[list[int], int]] = []

    def take(lengths: list[int]) -> None:
        kinds, uses = np.unique(lengths, return_counts=True)
        times = int((left[kinds] // uses).min())
        left[kinds] -= uses * times
        patterns.append((lengths, times))

    def pair(total: int, held: list[int]) -> list[int] | None:
        """The two lengths furthest apart of those that sum to ``total`` and are available."""
        if total < 2:
            return None
        free = left[: total + 1].copy()
        for n in held:
            if n <= total:
                free[n] -= 1
        small = np.arange(1, total // 2 + 1)
        ok = (free[small] > 0) & (free[total - small] > 0)
        if total % 2 == 0 and free[total // 2] < 2:
            ok[-1] = False
        hit = np.flatnonzero(ok)
        return [int(total - small[hit[0]]), int(small[hit[0]])] if len(hit) else None

    for n in range(size, 0, -1):
        gap = size - n
        while left[n] > 0:
            if gap == 0:
                take([n])
                continue
            if gap <= n and left[gap] > (gap == n):
                take([n, gap])
                continue
            two = pair(gap, [n])
            if two:
                take([n, *two])
                continue
            for one in range(min(gap - 2, n), 0, -1):
                if left[one] > (one == n) and (two := pair(gap - one, [n, one])):
                    take([n, one, *two])
                    break
            else:
                break
    while (left > 0).any():
        lengths, gap = [], size
        free = left.copy()
        while gap:
            fit = np.flatnonzero(free[: gap + 1] > 0)
            if not len(fit):
                break
            lengths.append(int(fit[-1]))
            free[fit[-1]] -= 1
            gap -= int(fit[-1])
        take(lengths)
    return patterns


def pack(docs: DataFrame, size: int = 1024, vocabulary_path: str | None = None, text: str = "text", key: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """Per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset (and ids)."""
    path = vocabulary_path or public_tokenizers.path("byte_bpe_50k.tiktoken")
    spark = docs.sparkSession
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    pieces = stored(rows.mapInArrow(lambda it: _encoded(it, path, size, with_ids), PIECES + (", ids array<long>" if with_ids else "")), "pieces")
    full = pieces.where(F.col("length") == size)
    pieces = pieces.where(F.col("length") < size)
    by_salt = pieces.groupBy("length", "salt").agg(F.count(F.lit(1)).alias("n"))
    table = sorted((r["length"], r["salt"], r["n"]) for r in by_salt.collect())  # at most size * SALTS rows
    counts = np.zeros(size + 1, np.int64)
    bases = []
    for length, salt, n in table:
        bases.append((length, salt, int(counts[length])))
        counts[length] += n
    used, slots, sequence = np.zeros(size + 1, np.int64), [], 0
    for lengths, times in plan_patterns(counts, size):
        at = 0
        for n in lengths:
            slots.append((n, int(used[n]), int(used[n]) + times, sequence, at))
            used[n] += times
            at += n
        sequence += times
    # Both tables are bounded by the histogram: size * SALTS bases and a few slots per length.
    base = spark.createDataFrame(bases, "length int, salt int, base long")
    slot = spark.createDataFrame(slots, "slot_length int, low long, high long, first_sequence long, offset long")
    within = Window.partitionBy("length", "salt").orderBy("ids_crc32", "doc_id", "piece")
    ranked = pieces.withColumn("k", F.row_number().over(within)).join(F.broadcast(base), ["length", "salt"]).withColumn("rank", F.col("base") + F.col("k") - 1)
    placed = ranked.join(F.broadcast(slot), (F.col("length") == F.col("slot_length")) & (F.col("rank") >= F.col("low")) & (F.col("rank") < F.col("high")))
    out = ["doc_id", "piece", "start", F.col("length").cast("long").alias("length"), "ids_crc32"]
    ids = ["ids"] if with_ids else []
    alone = full.select(*out, (-1 - F.monotonically_increasing_id()).alias("sequence_id"), F.lit(0).cast("long").alias("offset"), *ids)
    return placed.select(*out, (F.col("first_sequence") + F.col("rank") - F.col("low")).alias("sequence_id"), "offset", *ids).unionByName(alone)
