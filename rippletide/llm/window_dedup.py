"""Substring dedup: rolling hashes of every fixed-length word window, counted in Spark.

A window is ``WINDOW`` consecutive words of one text. Its Rabin-Karp hash comes from one prefix sum
over the row, so each further window costs two subtractions' worth of work. A word goes when a
window covering it has a word sequence that also starts in a document of smaller id; overlapping
windows merge into maximal intervals.

Shuffling every window would move several times the input, so exact steps narrow them first.
(1) Rows of equal word sequences keep one representative, the smallest id: every window of the
others repeats there. (2) Each window is represented by its least ``ANCHOR``-word hash; equal windows
have equal anchors, so a window whose anchor occurs in one document only cannot repeat. The anchors
that occur in several are a bitmap of fixed size, by which a scan emits windows; those it passes
wrongly find no equal. (3) Runs of windows that share an anchor are matched as a whole first: where a
smaller id has the same run, all of it goes; only runs of their smallest holder are matched window by
window. Keys are anchor and hash together (128 bits). Texts are shuffled only where words go.

A task holds one Arrow batch and the arrays of about ``CHUNK`` bytes of text (of one text, if longer).

Defined results: null text has no words; rows with a null doc_id keep all their words and remove
none elsewhere; rows repeating a doc_id never remove each other's words; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rippletide.llm.idbits import id_bitmap, maybe_in
from rippletide.llm.scratch import discard, stored
from rippletide.llm.skew import join_by_count
from rippletide.llm.textbytes import _POWERS, Words, list_column, mix, row_chunks, signed, text_buffer

WINDOW, ANCHOR = 13, 5
ANCHOR_BITS = 26
CHUNK = 1 << 18
EMPTY_SHA = hashlib.sha256(b"").hexdigest()


class Windows:
    """First word, anchor and hash of every window that lies within one row."""

    def __init__(self, words: Words) -> None:
        m = len(words.hashes)
        count = max(m - WINDOW + 1, 0)
        up, self.down = _POWERS.to(m + 1)
        self.sums = np.zeros(m + 1, np.uint64)
        np.cumsum(words.hashes * up[:m], out=self.sums[1:])
        least, span, need = words.grams(ANCHOR), 1, WINDOW - ANCHOR + 1
        while span < need and count:
            step = min(span, need - span)
            least = np.minimum(least[:-step], least[step:])
            span += step
        at = words.row_words
        end_of = np.repeat(at[1:], np.diff(at))
        self.first = np.flatnonzero(np.arange(count) + WINDOW <= end_of[:count])
        self.anchor = least[self.first]
        self.hashes = self.span_hash(self.first, self.first + WINDOW)
        self.row_cut = np.searchsorted(self.first, at)

    def span_hash(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return mix((self.sums[b] - self.sums[a]) * self.down[a] + (b - a).astype(np.uint64))


def _digests(words: Words) -> list:
    """SHA-256 of each row's words joined by one space."""
    text, at = words.joined()
    view = memoryview(text)
    return [hashlib.sha256(view[a:b]) for a, b in zip(at[:-1], at[1:], strict=True)]


def _mark(sha) -> int:
    return int.from_bytes(sha.digest()[:8], "little", signed=True)


def _profile(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Digest, number of words and distinct anchors of each row."""
    for batch in batches:
        data, offsets = text_buffer(batch.column(1))
        for i, j in row_chunks(offsets, CHUNK):
            words = Words(data, offsets[i : j + 1])
            w = Windows(words)
            shas = _digests(words)
            half = np.frombuffer(b"".join(s.digest()[:16] for s in shas), np.int64).reshape(-1, 2)
            anchors = [np.unique(w.anchor[a:b]) for a, b in zip(w.row_cut[:-1], w.row_cut[1:], strict=True)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).slice(i, j - i), pa.array(np.diff(words.row_words)), pa.array([s.hexdigest() for s in shas], pa.string()), pa.array(half[:, 0].copy()), pa.array(half[:, 1].copy()), list_column(signed(np.concatenate(anchors)), [len(a) for a in anchors])],
                names=["doc_id", "n_words", "sha", "d1", "d2", "anchors"],
            )


def _pruned(batches: Iterator[pa.RecordBatch], bitmap: np.ndarray) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        yield batch.filter(pa.array(maybe_in(bitmap, batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64))))


def _open_runs(batches: Iterator[pa.RecordBatch], first: np.ndarray, repeated: np.ndarray) -> Iterator[pa.RecordBatch]:
    """(doc_id, text) to the runs of windows of each first text whose anchor is in the bitmap."""
    for batch in _pruned(batches, first):
        ids = batch.column(0).to_numpy()
        data, offsets = text_buffer(batch.column(1))
        for i, j in row_chunks(offsets, CHUNK):
            words = Words(data, offsets[i : j + 1])
            w = Windows(words)
            hit = np.flatnonzero(maybe_in(repeated, signed(w.anchor)))
            if not len(hit):
                continue
            own = np.searchsorted(w.row_cut, hit, "right") - 1
            new = np.ones(len(hit), bool)
            new[1:] = (np.diff(hit) > 1) | (w.anchor[hit[1:]] != w.anchor[hit[:-1]]) | (own[1:] != own[:-1])
            at = np.flatnonzero(new)
            head, own = hit[at], own[at]
            size = np.diff(np.append(at, len(hit)))
            start = w.first[head]
            marks = np.array([_mark(s) for s in _digests(words)], np.int64)
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(ids[i + own]),
                    pa.array(marks[own]),
                    pa.array(signed(w.anchor[head])),
                    pa.array(signed(w.span_hash(start, start + size + WINDOW - 1))),
                    pa.array((start - words.row_words[own]).astype(np.int32)),
                    pa.array(size.astype(np.int32)),
                    list_column(signed(w.hashes[hit]), size),
                ],
                names=["doc_id", "d1", "a", "run", "pos", "size", "hs"],
            )


def covered(starts: np.ndarray, sizes: np.ndarray, n_words: int) -> np.ndarray:
    """Mask of the words that runs of ``sizes`` windows starting at these positions cover."""
    edge = np.zeros(n_words + 1, np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, np.minimum(starts + sizes + WINDOW - 1, n_words), -1)
    return np.cumsum(edge[:-1]) > 0


def _removed(batches: Iterator[pa.RecordBatch], with_text: bool) -> Iterator[pa.RecordBatch]:
    """(doc_id, text, mark, positions, sizes) to what is left of each text."""
    for batch in batches:
        data, offsets = text_buffer(batch.column(1))
        cuts = batch.column(3).offsets.to_numpy()
        starts, sizes = batch.column(3).values.to_numpy(), batch.column(4).values.to_numpy()
        for i, j in row_chunks(offsets, CHUNK):
            words = Words(data, offsets[i : j + 1])
            gone = np.zeros(len(words.hashes), bool)
            for k in range(i, j):
                lo, hi = words.row_words[k - i], words.row_words[k - i + 1]
                gone[lo:hi] = covered(starts[cuts[k] : cuts[k + 1]], sizes[cuts[k] : cuts[k + 1]], hi - lo)
            left, at = words.joined(~gone)
            view = memoryview(left)
            # A doc_id may have rows of other texts; the mark says whose positions these are.
            mine = np.array([_mark(s) for s in _digests(words)], np.int64) == batch.column(2).slice(i, j - i).to_numpy()
            out = np.concatenate([[0], np.cumsum(gone)])[words.row_words]
            shas = [hashlib.sha256(view[a:b]).hexdigest() for a, b in zip(at[:-1], at[1:], strict=True)]
            texts = [str(view[a:b], "utf-8", "replace") if with_text else None for a, b in zip(at[:-1], at[1:], strict=True)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).slice(i, j - i), batch.column(2).slice(i, j - i), pa.array(np.diff(out)), pa.array(shas, pa.string()), pa.array(texts, pa.string())],
                names=["doc_id", "d1", "n_removed", "kept_sha256", "kept_text"],
            ).filter(pa.array(mine))


def remove_repeated_windows(docs: DataFrame, text: str = "text", key: str = "doc_id", with_text: bool = True) -> tuple[DataFrame, DataFrame]:
    """Two tables: per row doc_id, n_words, n_removed, kept_sha256; and per partly shortened text
    doc_id, d1, n_removed, kept_sha256, kept_text (null unless ``with_text``)."""
    source = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    known = source.where("doc_id is not null")
    profile = stored(source.mapInArrow(_profile, "doc_id long, n_words long, sha string, d1 long, d2 long, anchors array<long>"), "profile")
    narrow = profile.where(f"doc_id is not null and n_words >= {WINDOW}").select("doc_id", "n_words", "d1", "d2")
    groups = stored(narrow.groupBy("d1", "d2").agg(F.min("doc_id").alias("first_id"), F.max("doc_id").alias("last_id"), F.count(F.lit(1)).alias("c")), "groups")
    copied = stored(groups.where("last_id > first_id"), "copied")
    copies = join_by_count(narrow, copied, ["d1", "d2"]).where("doc_id > first_id").select("doc_id", "d1", F.col("n_words").alias("r"), F.lit(EMPTY_SHA).alias("s"))

    first = id_bitmap(groups, "first_id")
    pruned = lambda rows, bitmap: rows.mapInArrow(lambda it: _pruned(it, bitmap), rows.schema)
    pieces = pruned(profile.where("doc_id is not null").select("doc_id", "anchors"), first).select(F.explode("anchors").alias("a"))
    repeated = id_bitmap(pieces.groupBy("a").agg(F.count(F.lit(1)).alias("c")).where("c > 1"), "a", ANCHOR_BITS)

    runs = stored(known.mapInArrow(lambda it: _open_runs(it, first, repeated), "doc_id long, d1 long, a long, run long, pos int, size int, hs array<long>"), "runs")
    least = stored(runs.groupBy("a", "run").agg(F.min("doc_id").alias("low"), F.count(F.lit(1)).alias("c")), "least")
    held = join_by_count(runs, least, ["a", "run"]).select("doc_id", "d1", "a", "pos", "size", F.when(F.col("doc_id") == F.col("low"), F.col("hs")).alias("hs"))
    held = stored(held, "held")
    discard(runs, least)
    whole = held.where("hs is null").select("doc_id", "d1", "pos", "size")
    windows = held.where("hs is not null").select("doc_id", "d1", "a", "pos", F.posexplode("hs").alias("k", "h"))
    twice = stored(windows.groupBy("a", "h").agg(F.min("doc_id").alias("low"), F.max("doc_id").alias("high"), F.count(F.lit(1)).alias("c")).where("high > low"), "twice")
    single = join_by_count(windows, twice.select("a", "h", "low", "c"), ["a", "h"]).where("doc_id > low").select("doc_id", "d1", (F.col("pos") + F.col("k")).alias("pos"), F.lit(1).alias("size"))
    cut = whole.union(single).groupBy("doc_id", "d1").agg(F.collect_list(F.struct("pos", "size")).alias("at"))
    cut = stored(cut.select("doc_id", "d1", F.col("at.pos").alias("at"), F.col("at.size").alias("sizes")), "cut")

    discard(held, twice)
    changed = id_bitmap(cut, "doc_id")
    shortened = stored(
        pruned(known, changed).join(cut, "doc_id").select("doc_id", "text", "d1", "at", "sizes").mapInArrow(lambda it: _removed(it, with_text), "doc_id long, d1 long, n_removed long, kept_sha256 string, kept_text string").dropDuplicates(["doc_id", "d1"]),
        "shortened",
    )
    discard(cut)
    changes = shortened.select("doc_id", "d1", F.col("n_removed").alias("r"), F.col("kept_sha256").alias("s")).union(copies).dropDuplicates(["doc_id", "d1"])
    out = profile.select("doc_id", "n_words", "sha", "d1").join(changes, ["doc_id", "d1"], "left")
    return out.select("doc_id", "n_words", F.coalesce("r", F.lit(0).cast("long")).alias("n_removed"), F.coalesce("s", "sha").alias("kept_sha256")), shortened
