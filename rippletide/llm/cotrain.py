"""Quality classifier by co-training two views of a page.

View one reads the text: which words and word beginnings occur, and its shape (shares of capitals,
symbols, bars and repeated lines). View two reads the metadata: source, language, length class. Both
are logistic models over hashed binary features. In each round a view labels those documents of an
unlabelled pool of which it is most sure, at most ``exchange`` a class and only beyond the confidence
at which it was right on held-out labels, and the other view trains on them too. On the held-out fold
each view is calibrated, and the calibrated views are weighed into one probability.

Training uses at most about ``sample`` labelled documents and as many for the pool, both chosen by a hash
of doc_id (the bound of what reaches the driver). Scoring is one scan of all documents.

A document is good if its quality label is 1 and it is not toxic. Defined results: labels with a null
doc_id or quality are ignored, a null toxic counts as 0, labels that repeat a document count by
majority (ties: good); with no or only one class of labels every document gets the score 0.5 and is
accepted; null text is empty, null source and lang are values of their own. Columns of ``keep`` that are
named like an output come out as ``in_<name>``.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rippletide.llm.scratch import stored
from rippletide.llm.textbytes import U, Words, list_column, row_chunks, text_buffer

OUT = ("doc_id", "text_score", "meta_score", "score", "accepted")
BITS = 18
CHUNK = 1 << 18
SIZE = 1 << BITS
NOT_WORD = np.ones(256, bool)
NOT_WORD[0x80:] = False
NOT_WORD[0x41:0x5B] = NOT_WORD[0x61:0x7B] = False
NOT_LINE = np.zeros(256, bool)
NOT_LINE[0x0A] = True


def _per_row(mask: np.ndarray, at: np.ndarray) -> np.ndarray:
    sums = np.concatenate([[0], np.cumsum(mask)])
    return sums[at[1:]] - sums[at[:-1]]


def text_features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct feature slots of the rows, and how many each row has."""
    n = len(offsets) - 1
    words = Words(data, offsets, lower=True, separator=NOT_WORD)
    row = np.repeat(np.arange(n), np.diff(words.row_words)).astype(np.uint64)
    parts = [(row << U(BITS)) | (h >> U(64 - BITS)) for h in (words.hashes, words.prefix_hashes(5) * U(0x9E3779B97F4A7C15))]
    at = offsets - offsets[0]
    raw = words.raw
    letters = ((raw >= 0x41) & (raw < 0x5B)) | ((raw >= 0x61) & (raw < 0x7B)) | (raw >= 0x80)
    capitals = (raw >= 0x41) & (raw < 0x5B)
    symbols = ~letters & (raw != 0x20) & (raw != 0x0A) & ~((raw >= 0x30) & (raw < 0x3A))
    size = np.maximum(np.diff(at), 1)
    lines = Words(data, offsets, separator=NOT_LINE)
    line_row = np.repeat(np.arange(n), np.diff(lines.row_words)).astype(np.uint64)
    keys = np.unique(np.stack([line_row, lines.hashes], axis=1), axis=0) if len(line_row) else np.zeros((0, 2), np.uint64)
    distinct = np.bincount(keys[:, 0].astype(np.int64), minlength=n)
    shares = [_per_row(capitals, at) / np.maximum(_per_row(letters, at), 1), _per_row(symbols, at) / size, _per_row(raw == 0x7C, at) / size, _per_row(raw == 0x21, at) / size, 1 - distinct / np.maximum(np.diff(lines.row_words), 1)]
    # The same shares of each row's most extreme line, so that one bad line in a long text shows.
    length = np.maximum(lines.ends - lines.starts, 1)
    full = np.flatnonzero(np.diff(lines.row_words))
    for mask in (capitals, symbols, raw == 0x7C, raw == 0x21):
        most = np.zeros(n)
        if len(full):
            sums = np.concatenate([[0], np.cumsum(mask)])
            most[full] = np.maximum.reduceat((sums[lines.ends] - sums[lines.starts]) / np.maximum(length, 40), lines.row_words[full])
        shares.append(most)
    # Words that repeat at once, and distinct words among all.
    same = np.zeros(len(row), bool)
    same[1:] = (words.hashes[1:] == words.hashes[:-1]) & (row[1:] == row[:-1])
    many = np.maximum(np.diff(words.row_words), 1)
    kinds = np.bincount((np.unique((row << U(40)) | (words.hashes >> U(24))) >> U(40)).astype(np.int64), minlength=n)
    shares += [np.bincount(row.astype(np.int64), same, n) / many, 1 - kinds / many]
    for k, share in enumerate(shares):
        level = np.minimum(np.sqrt(np.maximum(share, 0)) * 16, 15).astype(np.uint64)
        parts.append((np.arange(n, dtype=np.uint64) << U(BITS)) | (U(k * 16) + level))
    both = np.unique(np.concatenate(parts))
    return (both & U(SIZE - 1)).astype(np.int32), np.bincount((both >> U(BITS)).astype(np.int64), minlength=n)


def meta_features(sources: list, langs: list, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One slot each for source, language, length class, and source with length class."""
    slot = lambda s: zlib.crc32(s.encode()) >> (32 - BITS)
    rows = []
    for s, g, c in zip(sources, langs, np.log2(np.maximum(sizes, 1)).astype(int).tolist(), strict=True):
        rows += [slot(f"s{s}"), slot(f"l{g}"), slot(f"c{c}"), slot(f"s{s}c{c}")]
    return np.array(rows, np.int32), np.full(len(sources), 4)


class Logistic:
    """Logistic regression over sets of slots, fitted by full-batch adaptive gradient steps."""

    def __init__(self) -> None:
        self.w, self.b = np.zeros(SIZE, np.float32), 0.0

    def margin(self, slots: np.ndarray, counts: np.ndarray) -> np.ndarray:
        sums = np.concatenate([[0.0], np.cumsum(self.w[slots], dtype=np.float64)])
        ends = np.cumsum(counts)
        return self.b + sums[ends] - sums[ends - counts]

    def fit(self, slots: np.ndarray, counts: np.ndarray, y: np.ndarray, weight: np.ndarray, steps: int = 120, rate: float = 0.3, l2: float = 2e-4, least: int = 10, apart: float = 4.0) -> Logistic:
        """Only features of at least ``least`` rows whose shares in the two classes lie ``apart``
        standard errors from each other take part."""
        row = np.repeat(np.arange(len(counts)), counts)
        seen = np.bincount(slots, minlength=SIZE)
        ones = np.bincount(slots, y[row] == 1, SIZE)
        n1, n0 = max((y == 1).sum(), 1), max((y == 0).sum(), 1)
        p = np.clip(seen / len(y), 1e-9, 1 - 1e-9)
        z = (ones / n1 - (seen - ones) / n0) / np.sqrt(p * (1 - p) * (1 / n1 + 1 / n0))
        keep = ((seen >= least) & (np.abs(z) >= apart))[slots]
        slots, row = slots[keep], row[keep]
        w, b = np.zeros(SIZE), 0.0
        gw, gb = np.full(SIZE, 1e-6), 1e-6
        total = weight.sum()
        for _ in range(steps):
            z = np.bincount(row, w[slots], len(counts)) + b
            r = weight * (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) / total
            g = np.bincount(slots, r[row], SIZE) + l2 * w / 100
            gw += g * g
            gb += r.sum() ** 2
            w -= rate * g / np.sqrt(gw)
            b -= rate * r.sum() / gb**0.5
        self.w, self.b = w.astype(np.float32), float(b)
        return self


def _platt(z: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Coefficients (one a column of z, then a constant) of a small regularised logistic fit."""
    x = np.column_stack([z, np.ones(len(z))])
    c = np.zeros(x.shape[1])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ c, -30, 30)))
        h = (x * (p * (1 - p))[:, None]).T @ x + 1e-2 * np.eye(len(c))
        c -= np.linalg.solve(h, x.T @ (p - y) + 1e-2 * c)
    return c


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


@dataclass
class CoTrained:
    text: Logistic = field(default_factory=Logistic)
    meta: Logistic = field(default_factory=Logistic)
    text_scale: np.ndarray = field(default_factory=lambda: np.zeros(2))
    meta_scale: np.ndarray = field(default_factory=lambda: np.zeros(2))
    blend: np.ndarray = field(default_factory=lambda: np.zeros(3))
    fitted: bool = False
    held_out_accuracy: float = float("nan")
    exchanged: list = field(default_factory=list)


class _Rows:
    """Feature sets of some rows, selectable by index."""

    def __init__(self, slots: np.ndarray, counts: np.ndarray) -> None:
        self.slots, self.counts = slots, counts.astype(np.int64)
        self.start = np.cumsum(self.counts) - self.counts

    def at(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = self.counts[rows]
        inside = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        return self.slots[np.repeat(self.start[rows], n) + inside], n


def cotrain(text: _Rows, meta: _Rows, y: np.ndarray, rounds: int = 3, exchange: int = 200, sure: float = 0.97) -> CoTrained:
    """``y`` is 1, 0 or -1 (unlabelled) for each row."""
    model = CoTrained()
    labelled, pool = np.flatnonzero(y >= 0), np.flatnonzero(y < 0)
    held = labelled[np.arange(len(labelled)) % 5 == 0]
    train = labelled[np.arange(len(labelled)) % 5 != 0]
    if len({*y[train].tolist()}) < 2 or len({*y[held].tolist()}) < 2:
        return model
    views = [(text, "text"), (meta, "meta")]
    guess: list[dict[int, int]] = [{}, {}]
    for turn in range(rounds + 1):
        for (rows, name), own in zip(views, guess, strict=True):
            extra = np.array(sorted(own), np.int64)
            use = np.concatenate([train, extra])
            target = np.concatenate([y[train], [own[i] for i in extra]])
            balance = np.where(target == 1, 0.5 / max(target.mean(), 1e-9), 0.5 / max(1 - target.mean(), 1e-9))
            weight = balance * np.concatenate([np.ones(len(train)), np.full(len(extra), 0.5)])
            setattr(model, name, Logistic().fit(*rows.at(use), target, weight))
            z = getattr(model, name).margin(*rows.at(held))
            setattr(model, f"{name}_scale", _platt(z[:, None], y[held]))
        if turn == rounds:
            break
        given = []
        for (rows, name), other in zip(views, reversed(guess), strict=True):
            free = pool[[i not in other for i in pool.tolist()]] if len(pool) else pool
            a, c = getattr(model, f"{name}_scale")
            p = _sigmoid(a * getattr(model, name).margin(*rows.at(free)) + c) if len(free) else np.zeros(0)
            order = np.argsort(p, kind="stable")
            bad = [i for i in order[:exchange] if p[i] <= 1 - sure]
            good = [i for i in order[::-1][:exchange] if p[i] >= sure]
            other.update({int(free[i]): 0 for i in bad} | {int(free[i]): 1 for i in good})
            given.append(len(bad) + len(good))
        model.exchanged.append(tuple(given))
    z = np.column_stack([s[0] * v.margin(*r.at(held)) + s[1] for v, s, r in ((model.text, model.text_scale, text), (model.meta, model.meta_scale, meta))])
    model.blend = _platt(z, y[held])
    model.held_out_accuracy = float(((z @ model.blend[:2] + model.blend[2] > 0) == (y[held] == 1)).mean())
    model.fitted = True
    return model


def _batch_features(batch: pa.RecordBatch) -> Iterator[tuple[int, int, tuple, tuple]]:
    """(first row, end row, text features, metadata features); columns: doc_id, text, source, lang."""
    data, offsets = text_buffer(batch.column(1))
    sources, langs = batch.column(2).to_pylist(), batch.column(3).to_pylist()
    for i, j in row_chunks(offsets, CHUNK):
        yield i, j, text_features(data, offsets[i : j + 1]), meta_features(sources[i:j], langs[i:j], np.diff(offsets[i : j + 1]))


def _sampled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, t, m in _batch_features(batch):
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), list_column(t[0], t[1], pa.int32()), list_column(m[0], m[1], pa.int32()), batch.column(4).slice(i, j - i)], names=["doc_id", "t", "m", "y"])


def _view_columns(docs: DataFrame, text: str, key: str) -> list:
    of = lambda c: F.col(c).cast("string") if c in docs.columns else F.lit(None).cast("string")
    return [F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"), of("source").alias("source"), of("lang").alias("lang")]


def learn(docs: DataFrame, labels: DataFrame, sample: int = 6000, rounds: int = 3, text: str = "text", key: str = "doc_id") -> CoTrained:
    good = F.avg(((F.col("quality") == 1) & (F.coalesce("toxic", F.lit(0)) == 0)).cast("double")) >= 0.5
    marks = labels.where("doc_id is not null and quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(good.cast("int").alias("y"))
    marks = stored(marks, "labels")
    draw = F.pmod(F.xxhash64(F.lit("quality"), "doc_id"), F.lit(1 << 30))
    share = lambda n: int(min(1.0, sample / max(n, 1)) * (1 << 30))
    # Both bounded: about ``sample`` labels, and as many documents of the pool.
    known = F.broadcast(marks.where(draw < share(marks.count())))
    some = docs.select(*_view_columns(docs, text, key)).where("doc_id is not null").join(known, "doc_id", "left").where(F.col("y").isNotNull() | (draw < share(docs.count())))
    some = some.withColumn("y", F.coalesce("y", F.lit(-1)))
    table = some.mapInArrow(_sampled, "doc_id long, t array<int>, m array<int>, y int").toArrow().combine_chunks().sort_by("doc_id")
    if not table.num_rows:
        return CoTrained()
    sets = []
    for name in ("t", "m"):
        lists = table[name].combine_chunks()
        sets.append(_Rows(lists.flatten().to_numpy(), np.diff(lists.offsets.to_numpy())))
    return cotrain(*sets, table["y"].to_numpy(), rounds=rounds)


def _scored(batches: Iterator[pa.RecordBatch], model: CoTrained, threshold: float, kept: list[tuple[str, int]]) -> Iterator[pa.RecordBatch]:
    """``kept``: names of the columns that come along, and where they are."""
    for batch in batches:
        for i, j, t, m in _batch_features(batch):
            if model.fitted:
                z = [s[0] * v.margin(*f) + s[1] for v, s, f in ((model.text, model.text_scale, t), (model.meta, model.meta_scale, m))]
                p = _sigmoid(np.column_stack(z) @ model.blend[:2] + model.blend[2])
                views, ok = [_sigmoid(x) for x in z], p >= threshold
            else:
                p = np.full(j - i, 0.5)
                views, ok = [p, p], np.ones(j - i, bool)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), pa.array(views[0]), pa.array(views[1]), pa.array(p), pa.array(ok), *[batch.column(at).slice(i, j - i) for _, at in kept]], names=["doc_id", "text_score", "meta_score", "score", "accepted", *[name for name, _ in kept]])


def classify(docs: DataFrame, model: CoTrained, threshold: float = 0.5, text: str = "text", key: str = "doc_id", keep: list[str] | None = None) -> DataFrame:
    """Per row: doc_id, text_score, meta_score, score, accepted, and the columns of ``keep``."""
    views = {text: 1, "source": 2, "lang": 3}
    kept, more = [], []
    for c in keep or []:
        kind = docs.schema[c].dataType.simpleString()
        if c in views and kind == "string":  # travels as part of a view already
            kept.append((f"keep_{c}", kind, c, views[c]))
        else:
            kept.append((f"keep_{c}", kind, c, 4 + len(more)))
            more.append(F.col(c).alias(f"keep_{c}"))
    rows = docs.select(*_view_columns(docs, text, key), *more)
    schema = "doc_id long, text_score double, meta_score double, score double, accepted boolean" + "".join(f", {k} {t}" for k, t, _, _ in kept)
    places = [(k, at) for k, _, _, at in kept]
    out = rows.mapInArrow(lambda it: _scored(it, model, threshold, places), schema)
    return out.select("doc_id", "text_score", "meta_score", "score", "accepted", *[F.col(k).alias(f"in_{c}" if c in OUT else c) for k, _, c, _ in kept])
