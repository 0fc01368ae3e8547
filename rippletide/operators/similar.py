"""The graph of customers that agree on most of a few features, as classes of equal features.

Members of one class have the same neighbours but for themselves: degrees, sums over neighbours and label
propagation need one row a class. Arcs are made from lists of members where they are asked for and never pass
an exchange. A null feature agrees with nothing."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rippletide.functions.rng import pair_draws, u01
from rippletide.operators.graphs import InfluenceGraph
from rippletide.plans.storage import BROADCAST_ROWS, holding, small, stored
from rippletide.sources.tables import table

FEATURES = ["f1", "f2", "f3", "f4"]
#: About as many members in a list, and as many left members a task takes of a group that agrees.
LIST, SHARE = 512, 4096
#: About as many pairs whose draws are taken at once.
PAIRS = 1 << 17
#: What an arc counts where all features agree, and where all but one do.
SAME, NEAR = 1.0, 0.75


def features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, f1, f2, f3, f4): nation, segment, balance bin and order-count bin of every customer."""
    counts = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    return table(spark, sf_dir, "customer").join(counts, F.col("c_custkey") == F.col("o_custkey"), "left").select(
        F.col("c_custkey").alias("id"), F.col("c_nationkey").alias("f1"), F.col("c_mktsegment").alias("f2"), F.floor(F.col("c_acctbal") / 1000).cast("long").alias("f3"), F.floor(F.coalesce("n", F.lit(0)) / 4).cast("long").alias("f4")
    )


def complete(rows: DataFrame) -> DataFrame:
    return rows.where(" and ".join(f"{f} is not null" for f in FEATURES))


def _ways(rows: DataFrame, threshold: int) -> DataFrame:
    """rows once for each way to agree: on all features (way 0), or on all but feature ``way``, whose value
    is ``other``; ``key`` has what agrees."""
    kinds = dict(rows.dtypes)
    key = lambda way: F.struct(*[F.lit(None).cast(kinds[f]).alias(f) if f == f"f{way}" else F.col(f) for f in FEATURES])
    ways = [F.struct(F.lit(w).alias("way"), key(w).alias("key"), (F.col(f"f{w}").cast("string") if w else F.lit("")).alias("other")) for w in range(5 if threshold == 3 else 1)]
    rest = [c for c in rows.columns if c not in FEATURES]
    return rows.select(*rest, F.inline(F.array(*ways)))


def _lists(rows: DataFrame) -> DataFrame:
    """(f1..f4, part, rows): the other columns of a class's members, in lists."""
    rows = complete(rows)
    sizes = rows.groupBy(*FEATURES).agg(F.ceil(F.count(F.lit(1)) / LIST).alias("parts"))
    rest = [c for c in rows.columns if c not in FEATURES]
    return rows.join(sizes, FEATURES).groupBy(*FEATURES, F.pmod(F.xxhash64(rest[0]), "parts").alias("part")).agg(F.collect_list(F.struct(*rest)).alias("rows"))


def pairs(left: DataFrame, right: DataFrame, threshold: int = 3) -> DataFrame:
    """(columns of left and right but the features, p) of rows ``left`` (u, f1..f4, ..) and ``right``
    (v, f1..f4, ..) that agree on at least ``threshold`` features, u and v differing."""
    ours, theirs = [c for c in left.columns if c not in FEATURES], [c for c in right.columns if c not in FEATURES]
    met = _met(left, right, threshold)
    value = F.when(F.col("way") == 0, SAME).otherwise(NEAR).alias("p")
    out = met.select(value, "b", F.explode("a").alias("x")).select("p", "x", F.explode("b").alias("y"))
    return out.select(*[F.col(f"x.{c}") for c in ours], *[F.col(f"y.{c}") for c in theirs], "p").where("u <> v")


def _met(left: DataFrame, right: DataFrame, threshold: int = 3) -> DataFrame:
    """(way, a, b): lists a of left and b of right whose rows agree. Lists meet by what agrees; a large group
    is dealt by slices of its left lists."""
    if threshold not in (3, 4):
        raise ValueError("for thresholds 3 and 4")
    a, b = _ways(_lists(left), threshold), _ways(_lists(right), threshold)
    group = a.groupBy("way", "key").agg(F.ceil(F.sum(F.size("rows")) / SHARE).cast("int").alias("slices"))
    a = a.join(group, ["way", "key"]).select("way", "key", F.pmod(F.xxhash64("other", "part"), "slices").cast("int").alias("slice"), F.col("other").alias("a_other"), F.col("rows").alias("a"))
    b = b.join(group, ["way", "key"]).select("way", "key", F.explode(F.sequence(F.lit(0), F.col("slices") - 1)).alias("slice"), F.col("other").alias("b_other"), F.col("rows").alias("b"))
    return a.join(b, ["way", "key", "slice"]).where((F.col("way") == 0) | (F.col("a_other") != F.col("b_other"))).select("way", "a", "b")


def arcs(rows: DataFrame, threshold: int = 3) -> DataFrame:
    """(u, v, p) of all arcs; p is the share of the features that agree."""
    rows = stored(rows, "features")
    return pairs(rows.withColumnRenamed("id", "u"), rows.withColumnRenamed("id", "v"), threshold).select("u", "v", "p")


def neighbour_sums(rows: DataFrame, values: list[str], near: float = NEAR) -> DataFrame:
    """rows (f1..f4, n, values) with the sum of each of ``values`` over the neighbours of one member of the
    row as ``sum_<value>``, neighbours that agree on all but one feature times ``near``; null for a row with
    a null feature. A row stands for n members with the same values."""
    classes = complete(rows).groupBy(*FEATURES).agg(*[F.sum(F.col("n") * F.col(x)).alias(x) for x in values])
    around = lambda x: sum(F.sum(x).over(Window.partitionBy(*[f for f in FEATURES if f != drop])) for drop in FEATURES)
    classes = classes.select(*FEATURES, *[(SAME * F.col(x) + near * (around(x) - len(FEATURES) * F.col(x))).alias(f"sum_{x}") for x in values])
    return rows.join(classes, FEATURES, "left").withColumns({f"sum_{x}": F.col(f"sum_{x}") - F.col(x) for x in values})


def degrees(rows: DataFrame) -> DataFrame:
    """(f1..f4, n, degree): members of each class, and arcs out of each member."""
    classes = complete(rows).groupBy(*FEATURES).agg(F.count(F.lit(1)).alias("n"))
    return neighbour_sums(classes.withColumn("one", F.lit(1)), ["one"], 1).select(*FEATURES, "n", F.col("sum_one").cast("long").alias("degree"))


def propagate(rows: DataFrame, clamp: float = 0.5, tol: float = 1e-4, max_iter: int = 50, rounds: int | None = None) -> DataFrame:
    """(id, value) of ``churn.propagate_labels`` on ``arcs(rows)``, rows (id, f1..f4, label). Members of a class
    with the same label keep the same value, so a round has one row for each class and label."""
    state = complete(rows).groupBy(*FEATURES, "label").agg(F.count(F.lit(1)).alias("n")).withColumn("value", F.col("label"))
    state = stored(state.withColumn("one", F.lit(1.0)), "values")
    for _ in range(rounds or max_iter):
        mean = F.when(F.col("sum_one") > 0, F.col("sum_value") / F.col("sum_one"))
        new = neighbour_sums(state, ["value", "one"]).select(*FEATURES, "label", "n", "one", (clamp * F.col("label") + (1 - clamp) * F.coalesce(mean, "value")).alias("value"), F.col("value").alias("old"))
        new = stored(new, "values")
        state = new.drop("old")
        if rounds is None and (new.agg(F.max(F.abs(F.col("value") - F.col("old")))).first()[0] or 0.0) <= tol:
            break
    return rows.join(state.select(*FEATURES, "label", "value"), [*FEATURES, "label"], "left").select("id", F.coalesce("value", "label").alias("value"))


@dataclass(frozen=True)
class SimilarityGraph(InfluenceGraph):
    """The weighted-cascade graph (p = 1 / in-degree) with interactions drawn per arc. ``members`` is
    (id, f1..f4, o, p), p that of the arcs into a member, and ``heads`` their lists by what agrees; ``edges``
    has every arc, made anew on each use."""

    members: DataFrame
    heads: DataFrame
    mode: str

    def arcs_from(self, front: DataFrame, n: int) -> DataFrame:
        own = small(front.select(F.col("u").alias("id")).distinct(), n)
        starts = self.members.join(own, "id").select(F.col("id").alias("u"), *FEATURES)
        if 5 * n > BROADCAST_ROWS:
            return _cascade_arcs(starts, self.members, self.mode)
        a = _ways(complete(starts), 3).withColumnRenamed("other", "u_other")
        met = self.heads.join(F.broadcast(a), ["way", "key"]).where((F.col("way") == 0) | (F.col("other") != F.col("u_other")))
        return _drawn(met.select("u", F.inline("rows")).where("u <> v"), self.mode)


def _phi(mode: str) -> Column:
    return u01("phi", 1, F.col("u"), F.col("v"), mode=mode)


def _cascade_arcs(left: DataFrame, members: DataFrame, mode: str) -> DataFrame:
    return _drawn(pairs(left, _heads(members)), mode)


def _heads(members: DataFrame) -> DataFrame:
    return members.select(F.col("id").alias("v"), *FEATURES, F.col("p").alias("q"))


def _drawn(found: DataFrame, mode: str) -> DataFrame:
    return found.select("u", "v", F.col("q").alias("p"), F.lit(0.0).alias("w"), _phi(mode).alias("phi"))


def cascade_graph(rows: DataFrame, mode: str = "xxhash") -> SimilarityGraph:
    """From rows (id, f1..f4, o)."""
    p = degrees(rows).select(*FEATURES, F.try_divide(F.lit(1.0), "degree").alias("p"))
    members = stored(rows.join(p, FEATURES, "left").select("id", *FEATURES, "o", "p"), "members")
    nodes = members.select("id", "o", F.lit(0.5).alias("theta"))
    heads = stored(_ways(_lists(_heads(members)), 3), "heads")
    return SimilarityGraph(nodes, _cascade_arcs(members.select(F.col("id").alias("u"), *FEATURES), members, mode), members, heads, mode)


def _sums(members: DataFrame, vectors: DataFrame, names: list[str]) -> DataFrame:
    """(id, names): the sums of p times each vector over the heads of a node's arcs."""
    rows = members.join(vectors, "id", "left").select("id", *FEATURES, F.lit(1).alias("n"), *[F.coalesce(F.col(x) * F.col("p"), F.lit(0.0)).alias(x) for x in names])
    return neighbour_sums(rows, names, 1.0).select("id", *[F.coalesce(f"sum_{x}", F.lit(0.0)).alias(x) for x in names])


def _turned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(id, x): the sums of x (phi - 1/2) of each u over the lists (u, v, x) of rows, phi by md5. Rows are taken
    together up to a number of pairs."""
    for batch in batches:
        us, vs, xs = (batch.column(k) for k in ("u", "v", "x"))
        ends, heads = us.offsets.to_numpy().astype(np.int64), vs.offsets.to_numpy().astype(np.int64)
        ids, v, x = us.values.to_numpy(), vs.values.to_numpy(), xs.values.to_numpy()
        n, m = np.diff(ends), np.diff(heads)
        upto = np.cumsum(n * m)
        row = 0
        while row < len(n):
            last = max(row + 1, int(np.searchsorted(upto, (upto[row - 1] if row else 0) + PAIRS, "right")))
            count = (n * m)[row:last]
            which = np.repeat(np.arange(row, last), count)
            place = np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count)
            i = ends[which] - ends[row] + place // m[which]
            j = heads[which] - heads[row] + place % m[which]
            some, ours, theirs = ids[ends[row] : ends[last]], v[heads[row] : heads[last]], x[heads[row] : heads[last]]
            turn = np.where(some[i] != ours[j], theirs[j] * (pair_draws("phi|1", some, ours, i, j) - 0.5), 0.0)
            one, spot = np.unique(some, return_inverse=True)
            yield pa.RecordBatch.from_arrays([pa.array(one, pa.int64()), pa.array(np.bincount(spot[i], turn, len(one)), pa.float64())], names=["id", "x"])
            row = last


def _turned_sums(g: SimilarityGraph, vector: DataFrame, tails: DataFrame | None = None) -> DataFrame:
    """(id, x): the sums of p (phi - 1/2) x over the arcs of every node, or of ``tails`` (id), x of ``vector``
    (id, x); only heads with an x other than 0 are paired. Draws by md5 are taken for many pairs at once."""
    heads = g.members.join(vector.where("x <> 0"), "id").select(F.col("id").alias("v"), *FEATURES, (F.col("p") * F.col("x")).alias("x"))
    left = (g.members if tails is None else g.members.join(tails, "id", "left_semi")).select(F.col("id").alias("u"), *FEATURES)
    if g.mode != "md5":
        return pairs(left, heads).groupBy(F.col("u").alias("id")).agg(F.sum(F.col("x") * (_phi(g.mode) - 0.5)).alias("x"))
    # A head without an arc has no p; a null key is in no arc.
    lists = _met(left.where("u is not null"), heads.where("x is not null")).select(F.col("a.u").alias("u"), F.col("b.v").alias("v"), F.col("b.x").alias("x"))
    sums = lists.mapInArrow(_turned, "id long, x double").groupBy("id").agg(F.sum("x").alias("x"))
    # A task's work is in its pairs, not in its bytes.
    with holding(g.members.sparkSession, {"spark.sql.adaptive.coalescePartitions.enabled": "false", "spark.sql.execution.arrow.maxRecordsPerBatch": "1000"}):
        return stored(sums, "turns")


def _leaders(rows: DataFrame, g: SimilarityGraph, state: DataFrame) -> DataFrame:
    """rows (id, o, before, ends, carry) of the last step that may still have the largest score: phi - 1/2 is at most
    1/2 in size, so the sums of p |alpha| / 2 bound what the interactions can add or take."""
    bound = _sums(g.members.join(state.select("id"), "id", "left_semi"), state.select("id", F.abs("alpha").alias("alpha")), ["alpha"]).select("id", (F.col("alpha") / 2).alias("bound"))
    base, most = F.col("before") + (F.col("ends") + F.col("carry")) / 2, F.abs("o") * F.col("bound")
    both = stored(rows.join(bound, "id").withColumns({"low": base - most, "high": base + most}), "bounds")
    least = both.agg(F.max("low").alias("least"))
    near = F.col("high") >= F.col("least") - 1e-9 * (1 + F.abs("least"))
    return stored(both.join(F.broadcast(least)).where(F.coalesce(near, F.lit(True))).select(*rows.columns), "leaders")


def score_seeds(g: SimilarityGraph, k: int, max_len: int, opinion: bool = False, interaction: bool = True) -> DataFrame:
    """(rank, id, score) of ``score_greedy_seeds`` with ``discount="seed"`` on the same graph. All sums but those of
    the interactions need the classes only; later rounds take from the sums of interactions what the
    removed seed had part in. The last step's interactions are summed for those that may lead only."""
    from rippletide.operators.seeds import SEEDS, _best

    spark = g.members.sparkSession
    gone: list[int] = []
    out: list[tuple[int, int, float]] = []
    turned: dict[int, DataFrame] = {}
    zero = lambda c: F.coalesce(c, F.lit(0.0))
    for rank in range(1, k + 1):
        left = g.members.where(~F.col("id").isin(gone)) if gone else g.members
        own = left.select("id", F.col("o").cast("double").alias("o"))
        state = own.select("id", F.col("o").alias("ends"), F.lit(1.0).alias("alpha"), F.lit(0.0).alias("carry"), F.lit(0.0).alias("score"))
        lost = spark.createDataFrame([(gone[-1], 1.0)], "id long, x double") if gone else None
        for i in range(max_len):
            if not opinion:
                new = _sums(left, state.select("id", (1 + F.col("score")).alias("score")), ["score"]).withColumns({"ends": F.lit(0.0), "alpha": F.lit(0.0), "carry": F.lit(0.0)})
                state = stored(new.select(*state.columns), "score")
                continue
            sums = _sums(left, state, ["ends", "carry", "alpha"])
            rows = own.join(state.select("id", F.col("score").alias("before")), "id").join(sums.drop("alpha"), "id")
            if interaction and 0 < i == max_len - 1:
                rows = _leaders(rows, g, state)
                found = _turned_sums(g, state.select("id", F.col("alpha").alias("x")), rows.select("id"))
                alpha = rows.select("id").join(found, "id", "left").select("id", zero("x").alias("alpha"))
            elif interaction:
                if lost is None:
                    fresh = own.select("id").join(_turned_sums(g, state.select("id", F.col("alpha").alias("x"))), "id", "left").select("id", zero("x").alias("x"))
                    turned[i] = stored(fresh, "turned")
                else:
                    before = turned[i]
                    less = _turned_sums(g, lost)
                    both = stored(before.join(less.withColumnRenamed("x", "less"), "id", "left").select("id", F.col("x").alias("old"), F.when(F.col("id").isin(gone), 0.0).otherwise(F.col("x") - zero("less")).alias("x")), "turned")
                    lost = both.select("id", (F.col("old") - F.col("x")).alias("x")).where("x <> 0")
                    turned[i] = both.select("id", "x")
                alpha = turned[i].select("id", F.col("x").alias("alpha"))
            else:
                alpha = sums.select("id", (F.col("alpha") / 2).alias("alpha"))
            rows = rows.join(alpha, "id")
            turn = F.col("o") * F.col("alpha")
            state = stored(rows.select("id", "ends", "alpha", (F.col("carry") + turn).alias("carry"), (F.col("before") + (F.col("ends") + F.col("carry") + turn + turn) / 2).alias("score")), "score")
        best = _best(state, False)
        if best is None:
            break
        out.append((rank, *best))
        gone.append(best[0])
    return spark.createDataFrame(out, SEEDS)
