"""Document fingerprints as invertible Bloom lookup sketches, in built-in expressions only.

A text's units are its distinct paragraphs. Line breaks do not make them, since many texts have none:
a paragraph is a run of words that ends where a hash of two words is a multiple of 2**level, so that an
edit changes only the paragraphs it touches. A word is a run of at most ``LONGEST`` characters below
U+0E00 that are not white space, or one of the others (the scripts written without spaces are among
them), with the white space after it. The level grows with the number of words, so that a text has about ``UNITS`` paragraphs, and two
texts are compared at the higher of their levels, to which the lower one's paragraphs merge.

A paragraph's digest is 40 hash bits followed by 22 check bits of those,
and falls in one cell of each of ``TABLES`` sub-tables; a cell holds the XOR of its digests. Two
sketches subtract by XOR, cell by cell; digests in both vanish, and peeling (a cell whose check bits
fit holds a single digest, which is then taken out of its other cells) recovers the digests that only
one side has. If it gets stuck, the comparison is repeated on larger sketches: the digests are dealt
by hash to g groups of cells, g in proportion to their number, doubling up to ``RETRIES`` times.
(Should all fail, the digest arrays are compared.) Work stays linear in the digests.

The fingerprint is the sketch of ``BASE`` cells a table as text; equal texts have equal ones. The
likeness of two texts follows from the number d of recovered digests and the unit counts a and b as
(a + b - d) / (a + b + d), the Jaccard similarity of their units.

Defined results: null text is empty and its sketch has only empty cells; two empty texts have likeness
1. The next document follows in descending doc_id, rows of one doc_id by a hash of their texts, then by
text; after the last comes the first. A row with a null doc_id comes last. Every row is returned once;
other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TABLES, BASE = 3, 16
RETRIES, ROUNDS = 5, 24
CUTS, MAX_BLOCKS, BLOCK_ROWS = 8192, 1_000_000, 100
CHECK_BITS = 22
UNITS, LONGEST = 14, 10
WORD = rf"[!-~\u00A1-\u0DFF]{{1,{LONGEST}}}\s*|\S\s*|\s+"


def _let(value: Column, use) -> Column:
    """``use(value)`` with ``value`` evaluated once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _check(hashed: Column) -> Column:
    return F.xxhash64(hashed).bitwiseAND(F.lit((1 << CHECK_BITS) - 1))


def word_hashes(text: Column) -> Column:
    return F.transform(F.regexp_extract_all(text, F.lit(WORD), F.lit(0)), lambda w: F.xxhash64(w))


def level(hashes: Column) -> Column:
    """0, 1, 2, ...: about ``UNITS`` runs of 2**level words each."""
    return F.floor(F.log2(F.greatest(F.lit(1.0), F.size(hashes) / UNITS))).cast("int")


def _marked(hashes: Column, end: Column, at: Column) -> Column:
    """Whether the hash of a word and the one before has as many zero bits as the level says."""
    return F.get(hashes, end - 1).bitwiseXOR(F.shiftright(F.get(hashes, end - 2), 8)).bitwiseAND(at) == 0


def paragraph_ends(hashes: Column, at: Column) -> Column:
    """Numbers of the words that end a paragraph at a level, the last word's among them."""
    n = F.size(hashes)
    none = F.array().cast("array<int>")
    inner = F.when(n > 2, _let(_mask(at), lambda m: F.filter(F.sequence(F.lit(2), n - 1), lambda i: _marked(hashes, i, m)))).otherwise(none)
    return F.when(n > 0, F.concat(inner, F.array(n))).otherwise(none)


def _mask(at: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), at) - 1


def merged(hashes: Column, ends: Column, at: Column) -> Column:
    """The paragraph ends that also hold at a higher level."""
    return _let(_mask(at), lambda m: F.filter(ends, lambda e: (e == F.size(hashes)) | _marked(hashes, e, m)))


def unit_digests(hashes: Column, ends: Column) -> Column:
    """Sorted distinct digests of the paragraphs."""

    def digests(e: Column) -> Column:
        begin = lambda k: F.when(k == 0, 0).otherwise(F.get(e, k - 1))
        hashed = F.transform(e, lambda end, k: F.xxhash64(F.slice(hashes, begin(k) + 1, end - begin(k))).bitwiseAND(F.lit((1 << 40) - 1)))
        return F.array_sort(F.array_distinct(F.transform(hashed, lambda h: F.shiftleft(h, CHECK_BITS).bitwiseOR(_check(h)))))

    return _let(ends, digests)


def _bits(d: Column, table: int, low: int) -> Column:
    return F.shiftright(d, CHECK_BITS + 4 * table + low).bitwiseAND(F.lit(3).cast("long"))


def cells(digests: Column) -> Column:
    """array<bigint> of TABLES * BASE cells, each the XOR of the digests that fall there. A cell's number
    in its table is four bits of the digest, dealt out two by two."""
    four = F.sequence(F.lit(0).cast("long"), F.lit(3).cast("long"))
    zero = F.lit(0).cast("long")

    def quarter(some: Column, table: int) -> Column:
        return F.transform(four, lambda low: F.aggregate(some, zero, lambda x, d: F.when(_bits(d, table, 0) == low, x.bitwiseXOR(d)).otherwise(x)))

    def of(table: int) -> Column:
        return F.flatten(F.transform(four, lambda high: _let(F.filter(digests, lambda d: _bits(d, table, 2) == high), lambda some: quarter(some, table))))

    return F.concat(*[of(t) for t in range(TABLES)])


def subtract(one: Column, two: Column) -> Column:
    return F.zip_with(one, two, lambda p, q: p.bitwiseXOR(q))


def peel(difference: Column) -> Column:
    """struct <found: the recovered digests, done: whether every cell is empty>."""
    start = F.struct(difference.alias("cells"), F.array().cast("array<bigint>").alias("found"), F.lit(False).alias("stuck"))

    def pure(x: Column) -> Column:
        # An empty cell never is: the check bits of 0 are not all 0.
        return x.bitwiseXOR(F.xxhash64(F.shiftright(x, CHECK_BITS))).bitwiseAND(F.lit((1 << CHECK_BITS) - 1).cast("long")) == 0

    def without(state: Column, keys: Column) -> Column:
        left = F.when(F.size(keys) == 0, state["cells"]).otherwise(subtract(state["cells"], cells(keys)))
        return F.struct(left.alias("cells"), F.concat(state["found"], keys).alias("found"), (F.size(keys) == 0).alias("stuck"))

    def step(state: Column, _: Column) -> Column:
        return F.when(state["stuck"], state).otherwise(_let(F.array_distinct(F.filter(state["cells"], pure)), lambda keys: without(state, keys)))

    end = F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), start, step)
    return _let(end, lambda e: F.struct(e["found"].alias("found"), F.forall(e["cells"], lambda x: x == 0).alias("done")))


def apart(one: Column, two: Column, first: Column) -> Column:
    """How many unit digests two digest arrays do not share, recovered from their sketches; ``first`` is
    the difference of the sketches of one group."""

    def grouped(g: Column) -> Column:
        inside = lambda digests, j: F.filter(digests, lambda d: F.pmod(F.shiftright(d, 36), g) == j)
        parts = F.transform(F.sequence(F.lit(0).cast("long"), g - 1), lambda j: _let(F.struct(inside(one, j).alias("a"), inside(two, j).alias("b")), lambda s: peel(subtract(cells(s["a"]), cells(s["b"])))))
        return _let(parts, lambda all_: F.struct(F.forall(all_, lambda p: p["done"]).alias("done"), F.aggregate(all_, F.lit(0), lambda n, p: n + F.size(p["found"])).alias("d")))

    def step(state: Column, i: Column) -> Column:
        larger = F.ceil((F.size(one) + F.size(two)) / 32.0) * F.pow(F.lit(2.0), i)
        return F.when(state["done"], state).otherwise(_let(larger.cast("long"), grouped))

    start = _let(peel(first), lambda p: F.struct(p["done"].alias("done"), F.size(p["found"]).alias("d")))
    end = F.aggregate(F.sequence(F.lit(1), F.lit(RETRIES)), start, step)
    exact = F.size(F.array_except(one, two)) + F.size(F.array_except(two, one))
    return _let(end, lambda e: F.when(e["done"], e["d"]).otherwise(exact))


def likeness(one: Column, two: Column, d: Column) -> Column:
    total = F.size(one) + F.size(two)
    return F.when(total == 0, F.lit(1.0)).otherwise(_let(d, lambda n: (total - n) / (total + n)))


def fingerprint_text(sketch: Column) -> Column:
    return F.concat_ws(":", F.transform(sketch, lambda x: F.when(x == 0, F.lit("")).otherwise(F.hex(x))))


def with_units(rows: DataFrame, text: str, prefix: str) -> DataFrame:
    """``rows`` with the words, level and paragraph digests of a text column."""
    rows = rows.withColumn(f"{prefix}words", word_hashes(F.col(text)))
    rows = rows.withColumn(f"{prefix}level", level(F.col(f"{prefix}words")))
    rows = rows.withColumn(f"{prefix}ends", paragraph_ends(F.col(f"{prefix}words"), F.col(f"{prefix}level")))
    rows = rows.withColumn(f"{prefix}units", unit_digests(F.col(f"{prefix}words"), F.col(f"{prefix}ends")))
    return rows.withColumn(f"{prefix}sketch", cells(F.col(f"{prefix}units")))


def with_next(docs: DataFrame, text: str, key: str, cuts: int = CUTS, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(doc_id, t, words, level, ends, units, sketch, next: the same of the row that follows in descending doc_id). Rows are dealt to ranges of ids at approximate quantiles (at most ``cuts`` numbers reach the
    driver) and those to blocks of about ``block_rows`` rows: by id within the range, by the hash of the
    text in a range of one id. The row that follows a block's last is copied into the block, so that one
    exchange serves all; at most ``MAX_BLOCKS`` such ids are broadcast."""
    spark = docs.sparkSession
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("t"))
    rows = rows.withColumn("at", F.coalesce("doc_id", F.lit(-(1 << 63)))).withColumn("h", F.xxhash64("t"))
    n = rows.count()
    if not n:
        none = [F.array().cast("array<bigint>").alias("words"), F.lit(0).alias("level"), F.array().cast("array<int>").alias("ends"), *[F.array().cast("array<bigint>").alias(c) for c in ("units", "sketch")]]
        return rows.select("doc_id", "t", *none, F.struct("t", *none).alias("next"))
    wanted = min(MAX_BLOCKS, -(-n // block_rows))
    ranges = min(cuts, wanted)
    parts = -(-wanted // ranges)
    found = rows.agg(F.percentile_approx("at", [i / ranges for i in range(1, ranges)] or [0.5], 20 * ranges), F.min("at"), F.max("at")).first()
    cut, least, most = sorted(found[0]), found[1], found[2]
    # A value that two quantiles share has a range of its own, which ends one further.
    often = {a for a, b in zip(cut, cut[1:], strict=False) if a == b and a < most}
    bounds = sorted({least, *cut, *(e + 1 for e in often)})
    lows = F.from_json(F.lit(str(bounds)), "array<bigint>")
    steps = F.array(*[F.lit(1 << i) for i in reversed(range(len(bounds).bit_length()))])
    below = lambda i, s: F.when((i + s <= len(bounds)) & (F.get(lows, i + s - 1) <= F.col("at")), i + s).otherwise(i)
    rows = rows.withColumn("range", F.aggregate(steps, F.lit(0), below) - 1)
    low, high = F.get(lows, F.col("range")), F.get(lows, F.col("range") + 1)
    one_id = F.coalesce(high == low + 1, low == most)
    wide = F.greatest(F.coalesce(high, F.lit(most)).cast("double") - low.cast("double"), F.lit(1.0))
    by_id = F.floor((F.col("at").cast("double") - low.cast("double")) / wide * parts)
    by_text = F.lit(parts - 1) - F.floor((F.col("h") / 2.0**64 + 0.5) * parts)
    sub = F.greatest(F.lit(0), F.least(F.lit(parts - 1), F.when(one_id, by_text).otherwise(by_id)))
    rows = rows.withColumn("block", F.col("range") * parts + sub).drop("range")

    tops = rows.groupBy("block").agg(F.max(F.struct("at", F.bitwise_not("h").alias("g"))).alias("top"))
    down = Window.orderBy(F.desc("block"))
    every = down.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    donors = tops.select("block", "top.at", F.bitwise_not("top.g").alias("h"), F.coalesce(F.lag("block").over(down), F.last("block").over(every)).alias("to"))
    ghosts = rows.join(F.broadcast(donors), ["block", "at", "h"]).groupBy("to").agg(F.min("t").alias("t"))
    ghosts = ghosts.select(F.lit(None).cast("long").alias("doc_id"), "t", F.lit(0).cast("long").alias("at"), F.lit(0).cast("long").alias("h"), F.col("to").alias("block"), F.lit(1).alias("ghost"))
    both = rows.select("doc_id", "t", "at", "h", "block", F.lit(0).alias("ghost")).unionByName(ghosts).repartition("block")
    both = with_units(both, "t", "")
    order = Window.partitionBy("block").orderBy("ghost", F.desc("at"), "h", "t")
    both = both.withColumn("next", F.lead(F.struct("t", "words", "level", "ends", "units", "sketch")).over(order)).where("ghost = 0")
    return both.select("doc_id", "t", "words", "level", "ends", "units", "sketch", "next")


def fingerprints(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Per row: doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""
    rows = with_next(docs, text, key).withColumn("n_chars", F.length("t").cast("long"))
    half = F.floor(F.col("n_chars") / 2).cast("int")
    rows = rows.withColumn("edited", F.concat(F.substring(F.col("t"), F.lit(1), F.col("n_chars").cast("int") - half), F.substring(F.col("next.t"), F.lit(1), half)))
    rows = with_units(rows.withColumn("edited_sha256", F.sha2(F.col("edited").cast("binary"), 256)), "edited", "edited_")

    parts = ("words", "level", "ends", "units", "sketch")

    def raised(text: tuple, at: Column) -> Column:
        """Units and sketch of a text at its own or a higher level."""
        words, own, ends, units, sketch = text
        again = _let(unit_digests(words, merged(words, ends, at)), lambda u: F.struct(u.alias("u"), cells(u).alias("s")))
        return F.when(own >= at, F.struct(units.alias("u"), sketch.alias("s"))).otherwise(again)

    def near(prefix: str) -> Column:
        """Likeness to another text, both at the higher of their levels."""
        this, other = [F.col(c) for c in parts], [F.col(f"{prefix}{c}") for c in parts]
        both = F.struct(raised(this, other[1]).alias("a"), raised(other, this[1]).alias("b"))
        return _let(both, lambda s: likeness(s["a"]["u"], s["b"]["u"], apart(s["a"]["u"], s["b"]["u"], subtract(s["a"]["s"], s["b"]["s"]))))

    return rows.select(
        "doc_id",
        "n_chars",
        "edited_sha256",
        fingerprint_text(F.col("sketch")).alias("fingerprint"),
        fingerprint_text(F.col("edited_sketch")).alias("edited_fingerprint"),
        near("edited_").alias("near_edited"),
        near("next.").alias("near_next"),
    )
