"""Near-duplicate groups: banded MinHash candidates, pre-checked on odd sketches, confirmed exactly.

A document's set holds its distinct shingles of ``shingle`` lower-cased words. ``HASHES`` MinHash
samples of a set feed two things: ``BANDS`` band keys of ``ROWS`` samples each, and an odd sketch:
every sample flips one of ``SKETCH_BITS`` bits, so that a bit keeps the parity of its hits. The
population count of the XOR of two sketches estimates how many samples differ, most precisely at
high similarity. A candidate pair whose count lies beyond what a similarity of ``similarity`` can
give by chance (5.5 deviations) is dropped; all others are confirmed on the full sets.

At a similarity of 0.8 a pair shares no band with probability (1-0.8**5)**40 = 1.3e-7.

Groups of equal sets collapse to one representative first, so copies never pair. In a band bucket
each member is compared with the bucket's smallest id, then, where the bucket still spans several
components, with another member drawn by hash; what that leaves outside a bucket's main component is
compared with the whole bucket, in a join whose condition (first the sketches, then the full sets)
drops pairs before they become rows.

Defined results: null or blank text gives an empty set, linked with nothing; rows that repeat a
doc_id are one document, linked to whatever any of its texts links to; a row with a null doc_id
takes no part and is returned with a null component_id, kept true. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rippletide.llm.components import components
from rippletide.llm.idbits import id_bitmap, maybe_in
from rippletide.llm.scratch import stored
from rippletide.llm.textbytes import U, Words, list_column, mix, row_chunks, sequence_hash, signed, text_buffer

ROWS, BANDS = 5, 40
HASHES = ROWS * BANDS
SKETCH_BITS = 512
_rng = np.random.default_rng(77)
_MULTIPLIERS = _rng.integers(1, 2**63, HASHES, dtype=np.uint64) * U(2) + U(1)
_SALTS = _rng.integers(1, 2**63, HASHES, dtype=np.uint64)
SIGNATURE = "doc_id long, n_shingles long, d1 long, d2 long, bands array<long>, sketch array<long>"


def sketch_limit(similarity: float) -> int:
    """Largest XOR population count that a pair of at least this similarity can plausibly show: the
    expected count plus 5.5 deviations, those of the sampled differences and of the parity folding
    taken together."""
    apart = HASHES * (1 - similarity)
    kept = (1 - 2 / SKETCH_BITS) ** (2 * apart)
    sampling = 2 * kept * (HASHES * similarity * (1 - similarity)) ** 0.5
    folding = 2 * ((2 * apart) ** 2 / (2 * SKETCH_BITS)) ** 0.5
    return int(SKETCH_BITS * (1 - kept) / 2 + 5.5 * (sampling**2 + folding**2) ** 0.5) + 1


def shingle_sets(data: np.ndarray, offsets: np.ndarray, n: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each row."""
    words = Words(data, offsets, lower=True)
    grams, at, out = words.grams(n), words.row_words, []
    for a, b in zip(at[:-1], at[1:], strict=True):
        if b - a >= n:
            out.append(np.unique(grams[a : b - n + 1]))
        elif b > a:
            out.append(np.array([sequence_hash(words.hashes[a:b])], np.uint64))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def signatures(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Band keys (rows x BANDS) and packed odd sketches (rows x SKETCH_BITS/64) of non-empty sets."""
    flat = np.concatenate(sets)
    starts = np.cumsum([0, *(len(s) for s in sets[:-1])])
    samples = np.empty((len(sets), HASHES), np.uint64)
    for k in range(HASHES):
        samples[:, k] = np.minimum.reduceat(flat * _MULTIPLIERS[k], starts)
    salted = mix(samples + _SALTS)
    keys = np.zeros((len(sets), BANDS), np.uint64)
    for r in range(ROWS):
        keys = mix(keys * U(31) + salted[:, r * BANDS : (r + 1) * BANDS])
    bits = np.zeros((len(sets), SKETCH_BITS), np.uint8)
    rows, spot = np.arange(len(sets)), (salted % U(SKETCH_BITS)).astype(np.int64)
    for k in range(HASHES):
        bits[rows, spot[:, k]] ^= 1
    return keys, np.packbits(bits, axis=1).view(np.uint64)


def _signed_rows(batches: Iterator[pa.RecordBatch], n: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = batch.column(0)
        data, offsets = text_buffer(batch.column(1))
        for i, j in row_chunks(offsets):
            sets = shingle_sets(data, offsets[i : j + 1], n)
            full = [k for k, s in enumerate(sets) if len(s)]
            digest = np.zeros((j - i, 2), np.int64)
            bands, sketches = np.zeros(0, np.int64), np.zeros(0, np.int64)
            n_bands, n_words = np.zeros(j - i, int), np.zeros(j - i, int)
            if full:
                for k in full:
                    digest[k] = np.frombuffer(hashlib.blake2b(sets[k].tobytes(), digest_size=16).digest(), np.int64)
                keys, packed = signatures([sets[k] for k in full])
                bands, sketches = signed(keys.ravel()), signed(packed.ravel())
                n_bands[full], n_words[full] = BANDS, SKETCH_BITS // 64
            yield pa.RecordBatch.from_arrays(
                [ids.slice(i, j - i), pa.array([len(s) for s in sets], pa.int64()), pa.array(digest[:, 0]), pa.array(digest[:, 1]), list_column(bands, n_bands), list_column(sketches, n_words)],
                names=["doc_id", "n_shingles", "d1", "d2", "bands", "sketch"],
            )


def _set_rows(batches: Iterator[pa.RecordBatch], n: int, bitmap: np.ndarray) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        batch = batch.filter(pa.array(maybe_in(bitmap, batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64))))
        data, offsets = text_buffer(batch.column(1))
        for i, j in row_chunks(offsets):
            sets = shingle_sets(data, offsets[i : j + 1], n)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), list_column(signed(np.concatenate(sets)), [len(s) for s in sets])], names=["id", "grams"])


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) whose full sets have 100 * intersection >= percent * union."""
    left = sets.select(F.col("id").alias("a"), F.col("grams").alias("ga"))
    right = sets.select(F.col("id").alias("b"), F.col("grams").alias("gb"))
    both = F.size(F.array_intersect("ga", "gb"))
    return pairs.join(left, "a").join(right, "b").where(100 * both >= percent * (F.size("ga") + F.size("gb") - both)).select("a", "b").distinct()


def near_duplicates(docs: DataFrame, shingle: int = 5, percent: int = 80, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row per input row: doc_id, n_shingles, component_id, kept, class_id (the smallest id with
    the same set)."""
    source = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    signed_docs = stored(source.mapInArrow(lambda it: _signed_rows(it, shingle), SIGNATURE), "signatures")
    known = signed_docs.where("doc_id is not null")
    members = known.select("doc_id", "n_shingles", "d1", "d2")
    classes = members.where("n_shingles > 0").groupBy("d1", "d2").agg(F.min("doc_id").alias("class_id"))
    member_class = stored(
        members.join(classes, ["d1", "d2"], "left").select("doc_id", "n_shingles", F.coalesce("class_id", "doc_id").alias("class_id")), "classes"
    )

    heads = known.where("n_shingles > 0").join(member_class.where("doc_id = class_id").select("doc_id").distinct(), "doc_id", "left_semi")
    keys = heads.select(F.col("doc_id").alias("id"), F.explode("bands").alias("key"))
    hubs = keys.groupBy("key").agg(F.min("id").alias("hub"), F.max("id").alias("top")).where("top > hub").select("key", "hub")
    shared = stored(keys.join(hubs, "key"), "buckets")

    crowd = shared.select("id").distinct()
    bitmap = id_bitmap(crowd, "id")
    sets = stored(source.where("doc_id is not null").mapInArrow(lambda it: _set_rows(it, shingle, bitmap), "id long, grams array<long>").join(crowd, "id", "left_semi"), "sets")
    sketches = known.join(crowd.withColumnRenamed("id", "doc_id"), "doc_id", "left_semi").select(F.col("doc_id").alias("id"), F.col("n_shingles").alias("n"), F.col("sketch").alias("s"))

    stars = shared.where("id <> hub").select(F.col("id").alias("a"), F.col("hub").alias("b")).distinct()
    limit = sketch_limit(percent / 100)
    apart = sum((F.bit_count(F.get("sa", F.lit(i)).bitwiseXOR(F.get("sb", F.lit(i)))) for i in range(SKETCH_BITS // 64)), F.lit(0))
    alike = (100 * F.least("na", "nb") >= percent * F.greatest("na", "nb")) & (apart <= limit)
    of = lambda x: sketches.select(F.col("id").alias(x), F.col("n").alias("n" + x), F.col("s").alias("s" + x))
    near_hub = stars.join(of("a"), "a").join(of("b"), "b").where(alike).select("a", "b").distinct()
    links = stored(_confirmed(near_hub, sets, percent), "links")
    label = components(links)

    def open_buckets() -> DataFrame:
        """Members, with their components so far, of buckets that hold more than one."""
        marked = shared.join(label, "id", "left").select("key", "id", F.coalesce("component", "id").alias("c"))
        several = marked.groupBy("key").agg(F.min("c").alias("low"), F.max("c").alias("high")).where("low < high").select("key")
        return stored(marked.join(several, "key", "left_semi"), "open")

    # Another hub for each bucket, drawn by hash: members meet a different one in every band they share.
    opened = open_buckets()
    drawn = opened.groupBy("key").agg(F.min(F.struct(F.xxhash64("id", "key").alias("h"), "id", "c")).alias("w")).select("key", F.col("w.id").alias("b"), F.col("w.c").alias("cb"))
    again = opened.join(drawn, "key").where("c <> cb").select(F.least("id", "b").alias("a"), F.greatest("id", "b").alias("b")).distinct()
    second = _confirmed(again.join(of("a"), "a").join(of("b"), "b").where(alike).select("a", "b"), sets, percent)
    links = stored(links.union(second), "links")
    label = components(links)

    # What still lies apart: the smaller components' members against the whole bucket.
    opened = open_buckets()
    main = opened.groupBy("key", "c").count().groupBy("key").agg(F.max(F.struct("count", "c")).alias("w")).select("key", F.col("w.c").alias("main"))
    wide = stored(opened.join(main, "key").join(sketches, "id").join(sets, "id"), "open")
    side = lambda x: [F.col("id").alias(x), F.col("c").alias("c" + x), F.col("n").alias("n" + x), F.col("s").alias("s" + x), F.col("grams").alias("g" + x)]
    one = wide.where("c <> main").select("key", *side("a"))
    two = wide.select("key", "main", *side("b"))
    both = F.size(F.array_intersect("ga", "gb"))
    linked = 100 * both >= percent * (F.col("na") + F.col("nb") - both)
    once = (F.col("cb") == F.col("main")) | (F.col("a") < F.col("b"))
    third = one.join(two, (one["key"] == two["key"]) & (F.col("ca") != F.col("cb")) & once & alike & linked).select("a", "b").distinct()
    # A doc_id with several texts links the classes of all of them.
    lowest = member_class.groupBy("doc_id").agg(F.min("class_id").alias("low"), F.max("class_id").alias("high")).where("low < high")
    same = member_class.join(lowest.select("doc_id", "low"), "doc_id").where("class_id > low").select(F.col("low").alias("a"), F.col("class_id").alias("b")).distinct()
    label = components(links.union(third).union(same))

    done = member_class.join(label.select(F.col("id").alias("class_id"), "component"), "class_id", "left")
    whole = done.select("doc_id", "n_shingles", F.coalesce("component", "class_id").alias("component_id"), "class_id")
    return whole.withColumn("kept", F.col("doc_id") == F.col("component_id")).unionByName(
        signed_docs.where("doc_id is null").select("doc_id", "n_shingles", F.lit(None).cast("long").alias("component_id"), F.lit(None).cast("long").alias("class_id"), F.lit(True).alias("kept"))
    )
