"""Secret scans with corpus-wide ownership frequency, in built-in expressions only.

Candidates come from the base kinds (assign, access, hex) and from one more, ``token``: a run of 20 or
more of A-Za-z0-9_- that mixes upper case, lower case and digits and touches no base span. Each
distinct candidate value is counted by the repositories (documents) and owners (sources) that hold
it. A value that ``example_owners`` or more owners share is a widely copied example, and so is one that
at least two owners hold in ``example_repositories`` or more repositories; any other is owner-specific
and looks live. Token spans are added where live; base spans always stay.

Positions come without a scripting language: the gaps between a pattern's matches (``split``) and the
matches themselves (``regexp_extract_all``) alternate, so running sums of their lengths in code points
are the starts. Scans for spans run only on texts in which the pattern occurs at all.

Defined results: null text is empty; every input row is returned once, also with a null or repeated
doc_id; a null source is an owner of its own; counts are of base spans. Columns of ``keep`` that are named
like an output come out as ``in_<name>``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rippletide.llm.scratch import stored
from rippletide.llm.skew import join_by_count

# Fixed patterns. Group 2 of the first is the value; its letters match in either case.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{14,}"
HEX = r"[0-9a-f]{16,}"
TOKEN = r"(?<![A-Za-z0-9_-])(?=[A-Za-z0-9_-]*[a-z])(?=[A-Za-z0-9_-]*[A-Z])(?=[A-Za-z0-9_-]*[0-9])[A-Za-z0-9_-]{20,}"
KINDS = ("assign", "access", "hex", "token")
OUT = ("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_examples", "n_live", "found")
SPAN = "array<struct<s:int,k:int,e:int,v:string>>"


def _spans(text: Column, pattern: str, kind: int, value: Column | None = None) -> Column:
    """Array of (start, kind, end, value) of the leftmost matches that do not overlap."""
    hits = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    values = hits if value is None else F.regexp_extract_all(text, F.lit(pattern), value)
    gaps = F.split(text, pattern, -1)
    start = F.struct(F.lit(0).alias("at"), F.array().cast(SPAN).alias("out"))

    def step(acc: Column, x: Column) -> Column:
        begin = acc["at"] + F.length(x["g"])
        end = begin + F.length(x["h"])
        return F.struct(end.alias("at"), F.concat(acc["out"], F.array(F.struct(begin.alias("s"), F.lit(kind).alias("k"), end.alias("e"), x["v"].alias("v")))).alias("out"))

    rows = F.arrays_zip(F.slice(gaps, F.lit(1), F.size(hits)).alias("g"), hits.alias("h"), values.alias("v"))
    found = F.aggregate(rows, start, step)["out"]
    return F.when(text.rlike(pattern), found).otherwise(F.array().cast(SPAN))


def candidate_spans(text: Column) -> Column:
    """All candidates of a text, by start and then kind; struct<s, k, e, v>, end exclusive."""
    assign = F.filter(_spans(text, ASSIGN, 0, F.lit(2)), lambda x: F.length(x["v"]) >= 12)
    base = F.concat(assign, _spans(text, ACCESS, 1), _spans(text, HEX, 2))
    return F.array_sort(base)


def _token_spans(text: Column, base: Column) -> Column:
    return F.filter(_spans(text, TOKEN, 3), lambda t: ~F.exists(base, lambda b: (b["s"] < t["e"]) & (t["s"] < b["e"])))


def _is(k: int):
    return lambda x: x == k


def _listing(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.concat_ws(",", F.transform(spans, lambda x: F.concat_ws(":", F.get(names, x["k"]), x["s"].cast("string"), x["e"].cast("string"))))


def find_secrets(docs: DataFrame, example_owners: int = 5, example_repositories: int = 100, text: str = "text", key: str = "doc_id", owner: str = "source", keep: list[str] | None = None) -> DataFrame:
    """Per row: doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_examples (spans whose value is
    widely copied), n_live (the others), found (the spans as structs with ``live``), and ``keep``."""
    source = docs.select(
        F.col(key).cast("long").alias("doc_id"),
        F.col(owner).cast("string").alias("owner"),
        F.coalesce(F.col(text).cast("string"), F.lit("")).alias("t"),
        *[F.col(c).alias(f"keep_{c}") for c in keep or []],
    )
    base = source.withColumn("base", candidate_spans(F.col("t")))
    rows = base.withColumn("extra", _token_spans(F.col("t"), F.col("base")))
    hashed = F.transform(F.concat("base", "extra"), lambda x: F.struct(x["s"].alias("s"), x["k"].alias("k"), x["e"].alias("e"), F.sha2(x["v"], 256).alias("v")))
    rows = rows.select("doc_id", "owner", *[f"keep_{c}" for c in keep or []], hashed.alias("cands"), F.monotonically_increasing_id().alias("row"))
    rows = stored(rows, "candidates")

    some = rows.where(F.size("cands") > 0)
    spans = some.select("row", "owner", F.explode("cands").alias("x")).select("row", "owner", "x.s", "x.k", "x.e", "x.v")
    per_row = spans.groupBy("v", "owner", "row").agg(F.count(F.lit(1)).alias("c"))
    per_owner = per_row.groupBy("v", "owner").agg(F.count(F.lit(1)).alias("repositories"), F.sum("c").alias("c"))
    spread = stored(per_owner.groupBy("v").agg(F.count(F.lit(1)).alias("owners"), F.sum("repositories").alias("repositories"), F.sum("c").alias("c")), "spread")
    judged = join_by_count(spans.drop("owner"), spread, ["v"])
    live = ~((F.col("owners") >= example_owners) | ((F.col("owners") >= 2) & (F.col("repositories") >= example_repositories)))
    item = F.struct("s", "k", "e", live.alias("live"), "owners", "repositories")
    marked = judged.where((F.col("k") < 3) | live).groupBy("row").agg(F.array_sort(F.collect_list(item)).alias("found"))

    out = rows.join(marked, "row", "left")
    none = F.array().cast("array<struct<s:int,k:int,e:int,live:boolean,owners:bigint,repositories:bigint>>")
    out = out.withColumn("found", F.coalesce("found", none))
    count = lambda test: F.size(F.filter("found", test)).cast("long")
    return out.select(
        "doc_id",
        *[F.size(F.filter(F.col("found.k"), _is(k))).cast("long").alias(f"n_{KINDS[k]}") for k in range(3)],
        F.sha2(_listing(F.filter("found", lambda x: x["k"] < 3)).cast("binary"), 256).alias("base_sha256"),
        _listing(F.col("found")).alias("spans"),
        count(lambda x: ~x["live"]).alias("n_examples"),
        count(lambda x: x["live"]).alias("n_live"),
        "found",
        *[F.col(f"keep_{c}").alias(f"in_{c}" if c in OUT else c) for c in keep or []],
    )


def redact(text: Column, found: Column, mask: str = "[REDACTED]") -> Column:
    """``text`` with each live span, overlapping ones merged, replaced by ``mask``."""
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        inside = x["s"] < acc["at"]
        gap = F.when(inside, F.lit("")).otherwise(F.concat(F.substring(text, acc["at"] + 1, x["s"] - acc["at"]), F.lit(mask)))
        return F.struct(F.greatest(acc["at"], x["e"]).alias("at"), F.concat(acc["out"], gap).alias("out"))

    done = F.aggregate(F.filter(found, lambda x: x["live"]), start, step)
    return F.concat(done["out"], F.substring(text, done["at"] + 1, F.length(text)))
