"""Language identification by unigram piece models, marginalised over segmentations.

The pieces are those of a fixed public byte-level vocabulary. A language is a probability for each
piece; a word's probability is the sum over all its segmentations into pieces, found by a forward
pass over the word's bytes, and a text's is the product over its words. Piece probabilities are
fitted by expectation-maximisation on the same lattice, from word counts of a bounded sample of
labelled texts (about ``per_lang`` documents of each language, chosen by a hash of doc_id). Sums are
taken of logarithms, so that no word is too long and no language too unlikely for them.

Words are runs of bytes that are ASCII letters or belong to a longer character, in lower case (ASCII)
and led by a space, whatever their length. A model holds one column of piece probabilities a language.

Defined results: ``und`` with score 0 for a null text or one without a letter, or if no language could
be learned; ties go to the language that comes first by code point; a row with a null doc_id is
never learned from and not held out. Every row is returned once; other columns are ignored.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rippletide.llm.textbytes import LOWER, U, Words, row_chunks, text_buffer

FLOOR = 1e-7
HEAD = 16
BLOCK_BYTES = 1 << 18
NOT_LETTER = np.ones(256, bool)
NOT_LETTER[0x80:] = False
NOT_LETTER[0x41:0x5B] = NOT_LETTER[0x61:0x7B] = False
LETTER = regex.compile(r"\p{L}")
_BASE = 0x100000001B3
_SPREAD, _SHIFT = U(0x9E3779B97F4A7C15), U(42)


def vocabulary(path: str) -> list[bytes]:
    """Lower-case pieces of letters (with or without a leading space) and all single bytes."""
    with open(path, "rb") as lines:
        pieces = [base64.b64decode(line.split()[0]) for line in lines if line.strip()]
    fit = {p for p in pieces if p == p.lower() and not NOT_LETTER[np.frombuffer(p.lstrip(b" ") or b"a", np.uint8)].any()}
    return sorted(fit | {bytes([b]) for b in range(256)})


def _piece_hash(p: bytes) -> int:
    h = 0
    for b in p:
        h = (h * _BASE + b + 1) % 2**64
    return h


class Lattice:
    """All places where pieces occur in some words, grouped by end offset within the word."""

    def __init__(self, model: PieceModel, words: list[bytes]) -> None:
        sorted_hashes, piece_of, seen = model.sorted_hashes, model.piece_of, model.seen
        size = np.array([len(w) for w in words], np.int64)
        self.start = np.concatenate([[0], np.cumsum(size)])
        data = np.frombuffer(b"".join(words), np.uint8).astype(np.uint64) + U(1)
        place = np.arange(len(data)) - np.repeat(self.start[:-1], size)
        left = np.repeat(self.start[1:], size) - np.arange(len(data))
        self.n = len(data)
        begins, ends, pieces, offsets = [], [], [], []
        h = np.zeros(len(data), np.uint64)
        ok = np.arange(len(data))
        for length in range(1, model.longest + 1):
            ok = ok[left[ok] >= length]
            if not len(ok):
                break
            h[ok] = h[ok] * U(_BASE) + data[ok + length - 1]
            ok_likely = ok[seen[(h[ok] * _SPREAD) >> _SHIFT]]
            spot = np.searchsorted(sorted_hashes, h[ok_likely])
            spot[spot == len(sorted_hashes)] = 0
            hit = sorted_hashes[spot] == h[ok_likely]
            i = ok_likely[hit]
            begins.append(i)
            ends.append(i + length)
            pieces.append(piece_of[spot[hit]])
            offsets.append(place[i] + length)
            if length == HEAD:  # few pieces are longer: go on only where one may begin
                ok = ok[np.isin(h[ok], model.long_heads)]
        begin, end, self.piece = (np.concatenate(x) for x in (begins, ends, pieces))
        until = np.concatenate(offsets)
        # State k of a word sits at its start + k + (its number), so that words do not share states.
        self.word = number = np.repeat(np.arange(len(words)), size)[begin]
        self.begin, self.end = begin + number, end + number
        self.first = self.start[:-1] + np.arange(len(words))
        self.last = self.start[1:] + np.arange(len(words))
        self.states = self.n + len(words)
        self.by_end = self._groups(until, self.end)
        self.since = place[begin]

    def _groups(self, level: np.ndarray, state: np.ndarray) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """For each level: its edges in order of state, where each state's edges start, the states."""
        order = np.argsort(level * np.int64(self.states) + state, kind="stable")
        level, state = level[order], state[order]
        cut = np.flatnonzero(np.diff(level, prepend=-1))
        out = []
        for a, b in zip(cut, [*cut[1:], len(level)], strict=True):
            heads = np.flatnonzero(np.diff(state[a:b], prepend=-1))
            out.append((order[a:b], heads, state[a:b][heads]))
        return out

    def forward(self, logs: np.ndarray) -> np.ndarray:
        """logs: log piece probabilities (pieces x languages). Returns log sums, states x languages."""
        alpha = np.full((self.states, logs.shape[1]), -np.inf)
        alpha[self.first] = 0
        for edges, heads, states in self.by_end:
            alpha[states] = _log_sums(alpha[self.begin[edges]] + logs[self.piece[edges]], heads)
        return alpha

    def expected(self, logs: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Expected piece counts (pieces x languages) given word counts (words x languages)."""
        alpha = self.forward(logs)
        beta = np.full_like(alpha, -np.inf)
        beta[self.last] = -alpha[self.last]
        for edges, heads, states in reversed(self._groups(self.since, self.begin)):
            beta[states] = _log_sums(logs[self.piece[edges]] + beta[self.end[edges]], heads)
        flow = np.exp(alpha[self.begin] + logs[self.piece] + beta[self.end]) * counts[self.word]
        return np.stack([np.bincount(self.piece, flow[:, k], len(logs)) for k in range(logs.shape[1])], axis=1)


def _log_sums(x: np.ndarray, heads: np.ndarray) -> np.ndarray:
    """Logarithm of the sum of exp(x) over each group of rows."""
    top = np.maximum.reduceat(x, heads)
    return top + np.log(np.add.reduceat(np.exp(x - np.repeat(top, np.diff(np.append(heads, len(x))), axis=0)), heads))


def _blocks(words: list[bytes]) -> Iterator[tuple[int, int]]:
    """Ranges of words of about ``BLOCK_BYTES``; a longer word makes a range of its own."""
    ends = np.cumsum([len(w) for w in words])
    i = 0
    while i < len(words):
        j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + BLOCK_BYTES, "right")))
        yield i, j
        i = j


class PieceModel:
    """Piece probabilities of several languages over one vocabulary."""

    def __init__(self, pieces: list[bytes]) -> None:
        h = np.array([_piece_hash(p) for p in pieces], np.uint64)
        self.piece_of = np.argsort(h).astype(np.int64)
        self.sorted_hashes = h[self.piece_of]
        self.seen = np.zeros(1 << 22, bool)
        self.seen[(h * _SPREAD) >> _SHIFT] = True
        self.n_pieces = len(pieces)
        self.longest = max(map(len, pieces))
        self.long_heads = np.unique(np.array([_piece_hash(p[:HEAD]) for p in pieces if len(p) > HEAD], np.uint64))
        self.langs: list[str] = []
        self.logs = np.zeros((self.n_pieces, 0))

    def lattice(self, words: list[bytes]) -> Lattice:
        return Lattice(self, words)

    def fit(self, langs: list[str], words: list[bytes], counts: np.ndarray, rounds: int = 3) -> None:
        self.langs = langs
        p = np.full((self.n_pieces, len(langs)), 1.0 / self.n_pieces)
        blocks = [(self.lattice(words[i:j]), counts[i:j]) for i, j in _blocks(words)]
        for _ in range(rounds):
            use = np.zeros_like(p)
            for lattice, c in blocks:
                use += lattice.expected(np.log(p), c)
            p = np.maximum(use / np.maximum(use.sum(axis=0), 1e-9), FLOOR)
        self.logs = np.log(p / p.sum(axis=0))

    def word_scores(self, words: list[bytes]) -> np.ndarray:
        parts = [(x := self.lattice(words[i:j])).forward(self.logs)[x.last] for i, j in _blocks(words)]
        return np.concatenate(parts)


class Scorer:
    """Scores rows with a cache of word scores, emptied once it holds ``limit`` words."""

    def __init__(self, model: PieceModel, limit: int = 1_500_000) -> None:
        self.model, self.limit = model, limit
        self._clear()

    def _clear(self) -> None:
        self.keys = np.zeros(0, np.uint64)
        self.values = np.zeros((0, len(self.model.langs)))

    def score(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Log-probability of each row under each language."""
        words = Words(data, offsets, lower=True, separator=NOT_LETTER)
        out = np.zeros((len(offsets) - 1, len(self.model.langs)))
        if not len(words.hashes):
            return out
        uniq, where, back = np.unique(words.hashes, return_index=True, return_inverse=True)
        spot = np.searchsorted(self.keys, uniq)
        known = np.zeros(len(uniq), bool)
        inside = spot < len(self.keys)
        known[inside] = self.keys[spot[inside]] == uniq[inside]
        if not known.all():
            if len(self.keys) > self.limit:
                self._clear()
                known[:] = False
            fresh = np.flatnonzero(~known)
            for i in range(0, len(fresh), 20000):
                some = fresh[i : i + 20000]
                self.keys = np.concatenate([self.keys, uniq[some]])
                self.values = np.concatenate([self.values, self.model.word_scores([b" " + words.bytes[words.starts[w] : words.ends[w]].tobytes() for w in where[some]])])
            order = np.argsort(self.keys, kind="stable")
            self.keys, self.values = self.keys[order], self.values[order]
            spot = np.searchsorted(self.keys, uniq)
        per_word = self.values[spot][back]
        rows = np.repeat(np.arange(len(out)), np.diff(words.row_words))
        for lang in range(out.shape[1]):
            out[:, lang] = np.bincount(rows, per_word[:, lang], len(out))
        return out


def learn(docs: DataFrame, per_lang: int = 400, vocabulary_path: str | None = None, text: str = "text", lang: str = "lang", key: str = "doc_id", rounds: int = 3) -> PieceModel:
    """Fit on a sample of about ``per_lang`` documents per language, never of those held out. The
    languages' names and the sample's word counts are what reaches the driver."""
    model = PieceModel(vocabulary(vocabulary_path or public_tokenizers.path("byte_bpe_50k.tiktoken")))
    known = docs.select(F.col(lang).cast("string").alias("lang"), F.col(text).cast("string").alias("text"), F.col(key).cast("string").alias("id")).where(
        "lang is not null and text is not null and crc32(cast(id as binary)) % 4 <> 2"
    )
    sizes = known.groupBy("lang").count().collect()
    if not sizes:
        return model
    share = F.create_map(*[x for r in sizes for x in (F.lit(r["lang"]), F.lit(min(1.0, per_lang / r["count"])))])
    picked = known.where(F.pmod(F.xxhash64(F.lit("lang"), "id"), F.lit(1 << 20)) < F.coalesce(share[F.col("lang")], F.lit(0.0)) * (1 << 20))
    runs = F.regexp_extract_all(F.col("text"), F.lit("[A-Za-z\\x{80}-\\x{10FFFF}]+"), F.lit(0))
    counted = picked.select("lang", F.explode(runs).alias("w")).groupBy("lang", "w").count().toPandas()
    langs = sorted({r["lang"] for r in sizes} & set(counted["lang"]), key=lambda x: x.encode())
    index, words = {}, []
    rows: dict[bytes, np.ndarray] = {}
    for lg, w, c in zip(counted["lang"], counted["w"], counted["count"], strict=True):
        index.setdefault(lg, langs.index(lg))
        word = b" " + LOWER[np.frombuffer(w.encode(), np.uint8)].tobytes()
        if word not in rows:
            rows[word] = np.zeros(len(langs))
        rows[word][index[lg]] += c
    words = sorted(rows)
    if words:
        model.fit(langs, words, np.array([rows[w] for w in words]), rounds)
    return model


def _labelled(batches: Iterator[pa.RecordBatch], model: PieceModel) -> Iterator[pa.RecordBatch]:
    scorer = Scorer(model)
    names = np.array([*model.langs, "und"], object)
    for batch in batches:
        data, offsets = text_buffer(batch.column(1))
        for i, j in row_chunks(offsets, 4 << 20):
            best = np.full(j - i, len(model.langs))
            score = np.zeros(j - i)
            if model.langs:
                logs = scorer.score(data, offsets[i : j + 1])
                odds = np.exp(logs - logs.max(axis=1, keepdims=True))
                odds /= odds.sum(axis=1, keepdims=True)
                lettered = np.array([LETTER.search(data[offsets[k] : offsets[k + 1]].tobytes().decode("utf-8", "replace")) is not None for k in range(i, j)], bool)
                best = np.where(lettered, odds.argmax(axis=1), best)
                score = np.where(lettered, odds.max(axis=1), 0.0)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), batch.column(2).slice(i, j - i), pa.array(names[best].tolist(), pa.string()), pa.array(score)], names=["doc_id", "held_out", "lang_pred", "score"])


def identify(docs: DataFrame, model: PieceModel, text: str = "text", key: str = "doc_id") -> DataFrame:
    """doc_id, held_out, lang_pred, score of every row, in one scan without a shuffle."""
    out = F.coalesce(F.crc32(F.col(key).cast("string").cast("binary")) % 4 == 2, F.lit(False))
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"), out.alias("held_out"))
    return rows.mapInArrow(lambda it: _labelled(it, model), "doc_id long, held_out boolean, lang_pred string, score double")
