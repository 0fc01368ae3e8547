"""DuckDB SQL for the registered queries, generated per round or step from the same parameters."""

from __future__ import annotations


def u01(tag: str, seed: int, *cols: str) -> str:
    return f"(('0x'||substr(md5(concat_ws('|','{tag}','{seed}',{','.join(cols)})),1,8))::BIGINT/4294967296::DOUBLE)"


def r8(x: str) -> str:
    return f"(round({x},8)+0.0)"


def r6(x: str) -> str:
    return f"(round({x},6)+0.0)"


COPURCHASE = """op AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem),
cop AS (SELECT a.l_partkey u, b.l_partkey v, CAST(count(*) AS BIGINT) orders FROM op a JOIN op b USING (l_orderkey)
  WHERE a.l_partkey <> b.l_partkey GROUP BY 1, 2 HAVING count(*) >= 2)"""
SUCCESSION = """suc AS (SELECT u, v, CAST(count(*) AS BIGINT) weight FROM (SELECT lag(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) u, user_id v
  FROM events) WHERE u IS NOT NULL AND u <> v GROUP BY 1, 2 HAVING count(*) >= 2)"""


def graph_ctes(p: str = "0.1::DOUBLE", seed: int = 1, source: str = "cop") -> str:
    """Arcs ``e`` (u, v, p, w, phi) and nodes ``n`` (id, o) with md5 parameters."""
    return f"""{COPURCHASE if source == "cop" else SUCCESSION},
deg AS (SELECT v, count(*) d FROM {source} GROUP BY v),
e AS (SELECT u, v, {p} p, 1.0::DOUBLE/d w, {u01("phi", seed, "u", "v")} phi FROM {source} JOIN deg USING (v)),
n AS (SELECT id, 2*{u01("o", seed, "id")}-1 o FROM (SELECT u id FROM {source} UNION SELECT v FROM {source}))"""


def walk_rounds(max_len: int, edges: str = "e", prefix: str = "s") -> str:
    out = [f"{prefix}1 AS (SELECT u id, sum(p) score FROM {edges} GROUP BY u)"]
    for i in range(2, max_len + 1):
        out.append(f"{prefix}{i} AS (SELECT a.u id, sum(a.p*(1+coalesce(s.score,0))) score FROM {edges} a LEFT JOIN {prefix}{i - 1} s ON a.v=s.id GROUP BY a.u)")
    return ",\n".join(out)


def walk(max_len: int, p: str = "0.1::DOUBLE") -> str:
    return f"WITH {graph_ctes(p)},\n{walk_rounds(max_len)}\nSELECT n.id, {r6('coalesce(score,0)')} score FROM n LEFT JOIN s{max_len} s ON n.id=s.id"


def opinion_rounds(max_len: int, edges: str = "e", nodes: str = "n", prefix: str = "q") -> str:
    out = [f"{prefix}0 AS (SELECT id, o ends, 1.0::DOUBLE alpha, 0.0::DOUBLE carry, 0.0::DOUBLE score FROM {nodes})"]
    for i in range(1, max_len + 1):
        out.append(f"{prefix}x{i} AS (SELECT a.u id, sum(p*ends) ends, sum(p*alpha*(phi-0.5::DOUBLE)) alpha, sum(p*carry) carry FROM {edges} a JOIN {prefix}{i - 1} s ON a.v=s.id GROUP BY a.u)")
        out.append(
            f"{prefix}{i} AS (SELECT n.id, coalesce(x.ends,0) ends, coalesce(x.alpha,0) alpha, coalesce(x.carry,0)+n.o*coalesce(x.alpha,0) carry, b.score+(coalesce(x.ends,0)+coalesce(x.carry,0)+2*n.o*coalesce(x.alpha,0))/2 score FROM {nodes} n JOIN {prefix}{i - 1} b ON n.id=b.id LEFT JOIN {prefix}x{i} x ON n.id=x.id)"
        )
    return ",\n".join(out)


def opinion_walk(max_len: int) -> str:
    return f"WITH {graph_ctes()},\n{opinion_rounds(max_len)}\nSELECT id, {r6('score')} score FROM q{max_len}"


def union_walk(max_len: int) -> str:
    parts = ["m1 AS (SELECT u i, v j, p x FROM e)"]
    for k in range(2, max_len + 1):
        parts.append(f"m{k} AS (SELECT a.i, b.v j, 1-product(1-a.x*b.p) x FROM m{k - 1} a JOIN e b ON a.j=b.u WHERE a.i<>b.v GROUP BY 1, 2)")
    total = " UNION ALL ".join(f"SELECT i id, sum(x) s FROM m{k} GROUP BY i" for k in range(1, max_len + 1))
    return f"WITH {graph_ctes()},\n{', '.join(parts)}, t AS ({total}), z AS (SELECT id, sum(s) score FROM t GROUP BY id)\nSELECT n.id, {r6('coalesce(score,0)')} score FROM n LEFT JOIN z USING (id)"


def counts(max_len: int) -> str:
    parts = ["m1 AS (SELECT u, v, 1::BIGINT x FROM e)"]
    for k in range(2, max_len + 1):
        parts.append(f"m{k} AS (SELECT a.u, b.v, CAST(sum(a.x) AS BIGINT) x FROM m{k - 1} a JOIN e b ON a.v=b.u GROUP BY 1, 2)")
    total = " UNION ALL ".join(f"SELECT * FROM m{k}" for k in range(1, max_len + 1))
    return f"WITH {graph_ctes()}, {', '.join(parts)} SELECT u, v, CAST(sum(x) AS BIGINT) walks FROM ({total}) GROUP BY u, v"


def paths(max_len: int, edges: str = "e") -> str:
    """CTEs x1.. of simple paths (src, dst, path, x) and their union ``sp``."""
    out = [f"x1 AS (SELECT u src, v dst, [u, v] path, p x FROM {edges} WHERE u<>v)"]
    for k in range(2, max_len + 1):
        out.append(f"x{k} AS (SELECT src, b.v dst, list_append(path, b.v) path, x*p x FROM x{k - 1} a JOIN {edges} b ON a.dst=b.u WHERE NOT list_contains(path, b.v))")
    out.append("sp AS (" + " UNION ALL ".join(f"SELECT *, {k} length FROM x{k}" for k in range(1, max_len + 1)) + ")")
    return ", ".join(out)


def opinion_paths(max_len: int, lam: float) -> str:
    out = ["y0 AS (SELECT id src, id nd, 1.0::DOUBLE x, o op FROM n)"]
    for k in range(1, max_len + 1):
        out.append(f"y{k} AS (SELECT src, e.v nd, x*p x, (n.o+(2*phi-1)*op)/2 op FROM y{k - 1} y JOIN e ON y.nd=e.u JOIN n ON n.id=e.v)")
    total = " UNION ALL ".join(f"SELECT src id, x*CASE WHEN op<0 THEN {lam}::DOUBLE*op ELSE op END s FROM y{k}" for k in range(1, max_len + 1))
    return f"WITH {graph_ctes()}, {', '.join(out)}, t AS (SELECT id, sum(s) score FROM ({total}) GROUP BY id) SELECT n.id, {r6('coalesce(score,0)')} score FROM n LEFT JOIN t USING (id)"


TOP_DEGREE = "seeds AS (SELECT u id FROM e GROUP BY u ORDER BY count(*) DESC, u LIMIT 3)"
#: Unrolled steps of a cascade: more than any of those registered lasts (the longest ends at step 12).
STEPS = 24


def _starts(worlds: int, nodes: str, seeds: str, run: str) -> str:
    return f"SELECT {run}::BIGINT run, CAST(range AS INTEGER) world, s.id, 0 step, NULL::BIGINT parent, n.o o_final FROM range({worlds}), {seeds} s JOIN {nodes} n ON n.id=s.id"


def cascade_ic(worlds: int, steps: int = STEPS, seed: int = 1, interaction: bool = True, edges: str = "e", nodes: str = "n", seeds: str = "seeds", prefix: str = "", run: str = "0") -> str:
    """CTEs ending in ``{prefix}act`` (run, world, id, step, parent, o_final)."""
    p = prefix
    sign = f"CASE WHEN {u01('sign', seed, 'f.world', 'e.u', 'e.v')}<e.phi THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END" if interaction else "1.0::DOUBLE"
    out = [f"{p}f0 AS MATERIALIZED ({_starts(worlds, nodes, seeds, run)})", f"{p}a0 AS MATERIALIZED (SELECT * FROM {p}f0)"]
    for t in range(1, steps + 1):
        out.append(
            f"{p}f{t} AS MATERIALIZED (SELECT run, world, v id, {t} step, u parent, (n.o+turn)/2 o_final FROM (SELECT f.run, f.world, e.u, e.v, f.o_final*({sign}) turn, row_number() OVER (PARTITION BY f.run, f.world, e.v ORDER BY {u01('tie', seed, 'f.world', 'e.u', 'e.v')}, e.u) k FROM {p}f{t - 1} f JOIN {edges} e ON e.u=f.id WHERE {u01('ic', seed, 'f.world', 'e.u', 'e.v')}<e.p AND NOT EXISTS (SELECT 1 FROM {p}a{t - 1} a WHERE a.run=f.run AND a.world=f.world AND a.id=e.v)) JOIN {nodes} n ON n.id=v WHERE k=1)"
        )
        out.append(f"{p}a{t} AS MATERIALIZED (SELECT * FROM {p}a{t - 1} UNION ALL SELECT * FROM {p}f{t})")
    out.append(f"{p}act AS (SELECT * FROM {p}a{steps})")
    return ",\n".join(out)


def cascade_lt(worlds: int, steps: int = STEPS, seed: int = 1, interaction: bool = True, seeds: str = "seeds", prefix: str = "", run: str = "0") -> str:
    p = prefix
    sign = f"CASE WHEN {u01('sign', seed, 'a.world', 'e.u', 'e.v')}<e.phi THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END" if interaction else "1.0::DOUBLE"
    out = [f"{p}a0 AS MATERIALIZED ({_starts(worlds, 'n', seeds, run)})"]
    for t in range(1, steps + 1):
        out.append(
            f"{p}f{t} AS MATERIALIZED (SELECT run, world, v id, {t} step, parent, (n.o+turn)/2 o_final FROM (SELECT a.run, a.world, e.v, min(e.u) parent, avg(a.o_final*({sign})) turn, sum(e.w) w FROM {p}a{t - 1} a JOIN e ON e.u=a.id WHERE NOT EXISTS (SELECT 1 FROM {p}a{t - 1} b WHERE b.run=a.run AND b.world=a.world AND b.id=e.v) GROUP BY a.run, a.world, e.v HAVING sum(e.w)>={u01('theta', seed, 'a.world', 'e.v')}) JOIN n ON n.id=v)"
        )
        out.append(f"{p}a{t} AS MATERIALIZED (SELECT * FROM {p}a{t - 1} UNION ALL SELECT * FROM {p}f{t})")
    out.append(f"{p}act AS (SELECT * FROM {p}a{steps})")
    return ",\n".join(out)


ACT = f"SELECT world, id, step, parent, {r6('o_final')} o_final FROM act"


def reach(worlds: int, sources: str, kept: str) -> str:
    """Recursive ``rch`` (world, src, id): what each source reaches along ``kept`` (world, u, v)."""
    return f"rch(world, src, id) AS (SELECT CAST(range AS INTEGER), id, id FROM range({worlds}), {sources} UNION SELECT r.world, r.src, k.v FROM rch r JOIN {kept} k ON k.world=r.world AND k.u=r.id)"


def kept_ic(worlds: int, seed: int = 1) -> str:
    return f"kept AS MATERIALIZED (SELECT CAST(range AS INTEGER) world, u, v FROM range({worlds}), e WHERE {u01('ic', seed, 'range', 'u', 'v')}<p)"


LIVE = """spans AS (SELECT u, v, w, sum(w) OVER (PARTITION BY v ORDER BY u ROWS UNBOUNDED PRECEDING) high FROM e)"""


def kept_live(worlds: int, seed: int = 1) -> str:
    d = u01("live", seed, "range", "v")
    return f"{LIVE}, live AS MATERIALIZED (SELECT CAST(range AS INTEGER) world, u, v FROM range({worlds}), spans WHERE {d}>=high-w AND {d}<high)"


def greedy_by_score(k: int, max_len: int, opinion: bool, worlds: int = 0, steps: int = STEPS, seed: int = 1) -> str:
    """Unrolled score greedy; ``worlds`` > 0 takes away what is active in over half of the worlds."""
    parts = [graph_ctes()]
    edges, nodes, picks = "e", "n", []
    for r in range(1, k + 1):
        pre = f"g{r}"
        if opinion:
            parts.append(opinion_rounds(max_len, edges, nodes, pre + "q"))
            scored = f"SELECT id, score FROM {pre}q{max_len}"
        else:
            parts.append(walk_rounds(max_len, edges, pre + "s"))
            scored = f"SELECT n.id, coalesce(score,0) score FROM {nodes} n LEFT JOIN {pre}s{max_len} s ON s.id=n.id"
        parts.append(f"{pre}b AS MATERIALIZED (SELECT {r} rank, id, score FROM ({scored}) WHERE score>0 ORDER BY score DESC, id LIMIT 1)")
        picks.append(f"SELECT * FROM {pre}b")
        if r == k:
            break
        if worlds:
            parts.append(cascade_ic(worlds, steps, seed, True, edges, nodes, f"{pre}b", pre + "c"))
            gone = f"SELECT id FROM {pre}cact GROUP BY id HAVING count(*)>{worlds}/2.0 UNION SELECT id FROM {pre}b"
        else:
            gone = f"SELECT id FROM {pre}b"
        parts.append(f"{pre}x AS MATERIALIZED ({gone})")
        parts.append(f"{pre}e AS MATERIALIZED (SELECT * FROM {edges} WHERE u NOT IN (SELECT id FROM {pre}x) AND v NOT IN (SELECT id FROM {pre}x))")
        parts.append(f"{pre}n AS MATERIALIZED (SELECT * FROM {nodes} WHERE id NOT IN (SELECT id FROM {pre}x))")
        edges, nodes = f"{pre}e", f"{pre}n"
    return "WITH " + ",\n".join(parts) + f"\nSELECT rank, id, {r6('score')} score FROM ({' UNION ALL '.join(picks)})"


def mc_greedy(worlds: int) -> str:
    """The two best seeds of all nodes by the nodes that sets reach in common worlds."""
    return f"""WITH RECURSIVE {graph_ctes()}, {kept_ic(worlds)}, {reach(worlds, "n", "kept")},
all_ AS MATERIALIZED (SELECT * FROM rch),
one AS MATERIALIZED (SELECT 1 rank, src id, count(*)/{worlds}::DOUBLE-1 score FROM all_ GROUP BY src ORDER BY round(score,9) DESC, src LIMIT 1),
had AS MATERIALIZED (SELECT world, id FROM all_ WHERE src IN (SELECT id FROM one)),
more AS (SELECT src, count(*) c FROM all_ WHERE src NOT IN (SELECT id FROM one) AND NOT EXISTS (SELECT 1 FROM had WHERE had.world=all_.world AND had.id=all_.id) GROUP BY src),
sums AS (SELECT n.id, (h+coalesce(c,0))/{worlds}::DOUBLE-2 score FROM n CROSS JOIN (SELECT count(*) h FROM had) LEFT JOIN more ON src=n.id WHERE n.id NOT IN (SELECT id FROM one)),
two AS (SELECT 2 rank, id, score FROM sums ORDER BY round(score,9) DESC, id LIMIT 1)
SELECT rank, id, {r6("score")} score FROM (SELECT * FROM one UNION ALL SELECT * FROM two)"""


def opinion_greedy(worlds: int, lt: bool, interaction: bool) -> str:
    """The two best seeds of all nodes by simulated opinion spread: every candidate is a run."""

    def act(prefix: str, runs: str) -> str:
        if lt:
            return cascade_lt(worlds, STEPS, 1, interaction, runs, prefix, "s.run")
        return cascade_ic(worlds, STEPS, 1, interaction, seeds=runs, prefix=prefix, run="s.run")

    best = lambda rank, prefix: f"b{rank} AS MATERIALIZED (SELECT {rank} rank, run id, sum(CASE WHEN step>0 THEN o_final ELSE 0 END)/{worlds} score FROM {prefix}act GROUP BY run ORDER BY round(score,9) DESC, run LIMIT 1)"
    return f"""WITH {graph_ctes()}, r1 AS MATERIALIZED (SELECT id run, id FROM n), {act("x", "r1")}, {best(1, "x")},
r2 AS MATERIALIZED (SELECT n.id run, unnest([n.id, b1.id]) id FROM n, b1 WHERE n.id<>b1.id), {act("y", "r2")}, {best(2, "y")}
SELECT rank, id, {r6("score")} score FROM (SELECT * FROM b1 UNION ALL SELECT * FROM b2)"""


def rr_cover(count: int, k: int, seed: int = 1) -> str:
    parts = [
        graph_ctes("1.0::DOUBLE/d"),
        "ix AS (SELECT row_number() OVER (ORDER BY id)-1 k, id FROM n)",
        f"rrs(rr, id) AS (SELECT range, id FROM range({count}) JOIN ix ON k=floor({u01('root', seed, 'range')}*(SELECT count(*) FROM n)) UNION SELECT rr, e.u FROM rrs JOIN e ON e.v=id WHERE {u01('rr', seed, 'rr', 'e.u', 'e.v')}<p)",
        "l0 AS MATERIALIZED (SELECT * FROM rrs)",
    ]
    for r in range(1, k + 1):
        parts.append(f"b{r} AS MATERIALIZED (SELECT {r} rank, id, count(*)::DOUBLE score FROM l{r - 1} GROUP BY id ORDER BY count(*) DESC, id LIMIT 1)")
        parts.append(f"l{r} AS MATERIALIZED (SELECT * FROM l{r - 1} WHERE rr NOT IN (SELECT rr FROM l{r - 1} WHERE id IN (SELECT id FROM b{r})))")
    return "WITH RECURSIVE " + ",\n".join(parts) + " " + " UNION ALL ".join(f"SELECT * FROM b{r}" for r in range(1, k + 1))


def rank_rounds(rounds: int, alpha: float) -> str:
    out = ["k0 AS (SELECT id, 1.0::DOUBLE score FROM n)"]
    for i in range(1, rounds + 1):
        out.append(f"k{i} AS (SELECT n.id, 1+{alpha}::DOUBLE*coalesce(s,0) score FROM n LEFT JOIN (SELECT e.u id, sum(p*score) s FROM e JOIN k{i - 1} k ON k.id=e.v GROUP BY e.u) USING (id))")
    return ",\n".join(out)


POSTS = """posts AS (SELECT event_id, user_id, ts, CAST(json_extract_string(props,'$.k') AS INTEGER) topic,
  CASE WHEN event_type='view' THEN 0.0::DOUBLE WHEN event_type='error' THEN -(value/(value+50)) ELSE value/(value+50) END opinion FROM events),
gaps AS (SELECT *, (epoch_us(ts)-lag(epoch_us(ts)) OVER w)/1000000::DOUBLE gap FROM posts WINDOW w AS (PARTITION BY topic ORDER BY ts, event_id)),
lim AS (SELECT topic, avg(gap)+2*coalesce(stddev_pop(gap),0) threshold FROM gaps GROUP BY topic),
ep AS (SELECT event_id, user_id, ts, topic, opinion, CAST(sum(CASE WHEN gap>threshold THEN 1 ELSE 0 END) OVER (PARTITION BY topic ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) epoch FROM gaps JOIN lim USING (topic)),
mem AS MATERIALIZED (SELECT topic, epoch, user_id, min(ts) first_ts, avg(opinion) opinion FROM ep GROUP BY 1, 2, 3)"""
TOPIC_EDGES = f"""{SUCCESSION}, {POSTS},
te AS MATERIALIZED (SELECT a.topic, a.epoch, suc.u, suc.v FROM suc JOIN mem a ON a.user_id=suc.u JOIN mem b ON b.user_id=suc.v AND a.topic=b.topic AND a.epoch=b.epoch),
org AS (SELECT topic, epoch, user_id FROM mem m WHERE NOT EXISTS (SELECT 1 FROM te WHERE te.topic=m.topic AND te.epoch=m.epoch AND te.v=m.user_id))"""
SEED_EPOCHS = f"""WITH RECURSIVE {SUCCESSION}, {POSTS},
o AS MATERIALIZED (SELECT p.topic, p.event_id, p.user_id, epoch_us(p.ts)/1000000::DOUBLE now, threshold, coalesce(src, []::BIGINT[]) src, row_number() OVER (PARTITION BY p.topic ORDER BY p.ts, p.event_id) i
  FROM posts p JOIN lim USING (topic) LEFT JOIN (SELECT v, list(u) src FROM suc GROUP BY v) ON v=p.user_id),
f(topic, i, epoch, last, members) AS (SELECT topic, i, 0::BIGINT, now, [user_id] FROM o WHERE i=1
  UNION ALL SELECT topic, i, epoch, CASE WHEN NOT list_contains(m, user_id) AND (l IS NULL OR NOT list_has_any(src, m)) THEN now ELSE l END, CASE WHEN list_contains(m, user_id) THEN m ELSE list_append(m, user_id) END
  FROM (SELECT o.topic, o.i, o.user_id, o.now, o.src, f.epoch+(o.now-f.last>o.threshold)::BIGINT epoch, CASE WHEN o.now-f.last>o.threshold THEN NULL ELSE f.last END l, CASE WHEN o.now-f.last>o.threshold THEN []::BIGINT[] ELSE f.members END m FROM f JOIN o ON o.topic=f.topic AND o.i=f.i+1))
SELECT topic, epoch, CAST(count(*) AS BIGINT) posts FROM f GROUP BY 1, 2"""
ESTIMATE = """est AS (SELECT o.topic, o.user_id, max(o.truth) truth, sum(exp(-age)*past)/sum(exp(-age)) estimate FROM (SELECT o.topic, o.user_id, o.truth, p.opinion past, (epoch_us(o.first_ts)-epoch_us(p.ts))/(86400000000.0::DOUBLE*10) age
  FROM (SELECT topic, user_id, avg(opinion) truth, min(ts) first_ts FROM posts GROUP BY 1, 2) o JOIN posts p ON p.user_id=o.user_id AND p.topic//10=o.topic//10 AND p.topic<>o.topic AND p.ts<o.first_ts) o GROUP BY 1, 2)"""
SIMILARITY = """feat AS (SELECT c_custkey id, c_nationkey f1, c_mktsegment f2, CAST(floor(c_acctbal/1000) AS BIGINT) f3, CAST(floor(coalesce(n,0)/4) AS BIGINT) f4 FROM customer LEFT JOIN (SELECT o_custkey, count(*) n FROM orders GROUP BY 1) ON o_custkey=c_custkey),
sim AS (SELECT a.id u, b.id v, ((a.f1=b.f1)::INT+(a.f2=b.f2)::INT+(a.f3=b.f3)::INT+(a.f4=b.f4)::INT)/4.0::DOUBLE p FROM feat a JOIN feat b ON a.id<>b.id AND ((a.f1=b.f1)::INT+(a.f2=b.f2)::INT+(a.f3=b.f3)::INT+(a.f4=b.f4)::INT)>=3)"""
PATH_COUNTS = """op AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem),
pc AS (SELECT DISTINCT CAST(count(*) AS BIGINT) t FROM op JOIN orders ON o_orderkey=l_orderkey JOIN customer ON c_custkey=o_custkey GROUP BY c_nationkey, l_partkey)"""
LABELS = """lab AS (SELECT c_custkey id, CASE WHEN max(o_orderdate)>=TIMESTAMP '2001-01-01' THEN 1 ELSE -1 END label FROM customer LEFT JOIN orders ON o_custkey=c_custkey GROUP BY 1)"""


def propagation(rounds: int) -> str:
    out = ["v0 AS (SELECT id, label::DOUBLE val FROM lab)"]
    for i in range(1, rounds + 1):
        out.append(f"v{i} AS (SELECT l.id, 0.5::DOUBLE*l.label+0.5::DOUBLE*coalesce(m.m, o.val) val FROM lab l JOIN v{i - 1} o ON o.id=l.id LEFT JOIN (SELECT sim.v id, sum(p*x.val)/sum(p) m FROM sim JOIN v{i - 1} x ON x.id=sim.u GROUP BY 1) m ON m.id=l.id)")
    return ",\n".join(out)


TOY = """arcs(i,u,v,p,phi) AS (VALUES (0,1,4,0.8::DOUBLE,0.9::DOUBLE),(1,2,1,0.1,0.7),(2,2,3,0.1,0.8),(3,3,4,0.9,0.1)),
nodes(id,o) AS (VALUES (1::BIGINT,0.8::DOUBLE),(2,0.0),(3,0.6),(4,-0.3))"""
EXACT_TOY = f"""live AS (SELECT range world, u, v, phi FROM range(16), arcs WHERE ((range>>i)&1)=1),
wt AS (SELECT range world, product(CASE WHEN ((range>>i)&1)=1 THEN p ELSE 1-p END) weight FROM range(16), arcs GROUP BY 1),
rc(world, src, id) AS (SELECT range, id, id FROM range(16), nodes UNION SELECT rc.world, src, v FROM rc JOIN live ON live.world=rc.world AND live.u=rc.id),
toy_spread AS (SELECT src id, {r6('coalesce(sum(weight) FILTER (WHERE rc.id<>src),0)')} spread FROM rc JOIN wt USING (world) GROUP BY src)"""


def exact_opinion_toy() -> str:
    """All worlds of the worked example; simultaneous activators average, signs enter by expectation."""
    steps = ["h0 AS (SELECT range world, id src, id, o op FROM range(16), nodes)", "k0 AS (SELECT * FROM h0)"]
    for t in (1, 2, 3):
        steps.append(f"h{t} AS MATERIALIZED (SELECT l.world, f.src, l.v::BIGINT id, (any_value(n.o)+avg((2*l.phi-1)*f.op))/2 op FROM h{t - 1} f JOIN live l ON l.world=f.world AND l.u=f.id JOIN nodes n ON n.id=l.v WHERE NOT EXISTS (SELECT 1 FROM k{t - 1} k WHERE k.world=f.world AND k.src=f.src AND k.id=l.v) GROUP BY 1, 2, 3)")
        steps.append(f"k{t} AS MATERIALIZED (SELECT * FROM k{t - 1} UNION ALL SELECT * FROM h{t})")
    return f"WITH RECURSIVE {TOY}, {EXACT_TOY}, {', '.join(steps)} SELECT src id, {r6('coalesce(sum(weight*op) FILTER (WHERE k3.id<>src),0)')} spread FROM k3 JOIN wt USING (world) GROUP BY src"


PATHS = f"""WITH RECURSIVE c AS (SELECT conv_id path_id, conv_id*1000000+turn id, row_number() OVER (PARTITION BY conv_id ORDER BY turn)-1 pos FROM conversations),
x AS (SELECT a.path_id, a.pos, 2*{u01('o', 1, 'a.id')}-1 o, {u01('phi', 1, 'b.id', 'a.id')} phi FROM c a LEFT JOIN c b ON b.path_id=a.path_id AND b.pos=a.pos-1),
w(path_id, pos, prob, op, total) AS (SELECT path_id, pos, 1.0::DOUBLE, o, 0.0::DOUBLE FROM x WHERE pos=0 UNION ALL SELECT x.path_id, x.pos, prob*0.5::DOUBLE, (x.o+(2*x.phi-1)*op)/2, total+prob*0.5::DOUBLE*(x.o+(2*x.phi-1)*op)/2 FROM w JOIN x ON x.path_id=w.path_id AND x.pos=w.pos+1)
SELECT path_id, {r6('arg_max(total, pos)')} spread FROM w GROUP BY 1"""
TREE = """tree AS (SELECT n_regionkey::BIGINT u, n_nationkey+1000000000000 v FROM nation UNION ALL SELECT c_nationkey+1000000000000, c_custkey+2000000000000 FROM customer UNION ALL SELECT o_custkey+2000000000000, o_orderkey+3000000000000 FROM orders)"""
DAG = """dag AS (SELECT o_custkey+2000000000000 u, o_orderkey+3000000000000 v FROM orders UNION ALL SELECT DISTINCT l_orderkey+3000000000000, l_partkey+4000000000000 FROM lineitem)"""


def sql() -> dict[str, str]:
    base = graph_ctes()
    ic = f"WITH {base}, {TOP_DEGREE}, {cascade_ic(8)}"
    out = {
        "graph_copurchase": f"WITH {COPURCHASE} SELECT * FROM cop",
        "graph_succession": f"WITH {SUCCESSION} SELECT * FROM suc",
        "graph_trade": "SELECT o_custkey u, l_suppkey+1000000000000 v, CAST(count(*) AS BIGINT) lines FROM orders JOIN lineitem ON l_orderkey=o_orderkey GROUP BY 1, 2 HAVING count(*)>=2",
        "graph_tree": f"WITH {TREE} SELECT * FROM tree",
        "graph_order_dag": f"WITH {DAG} SELECT * FROM dag",
        "graph_conversation_paths": "SELECT conv_id*1000000+turn u, conv_id*1000000+nxt v FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) nxt FROM conversations) WHERE nxt IS NOT NULL",
        "graph_similarity": f"WITH {SIMILARITY} SELECT * FROM sim",
        "graph_embedding": f"WITH x AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) v FROM embeddings), c AS (SELECT a.vec_id u, b.vec_id v, list_cosine_similarity(a.v, b.v) p FROM x a, x b WHERE a.vec_id<>b.vec_id) SELECT u, v, {r6('p')} p FROM c WHERE p>=0.3",
        "graph_links": "SELECT page_id, href, CAST(count(*) AS BIGINT) links FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) href FROM pages) GROUP BY 1, 2",
        "graph_copies": "WITH h AS (SELECT text, min(doc_id) hub FROM documents GROUP BY text HAVING count(*)>1), p AS (SELECT hub u, doc_id v FROM documents JOIN h USING (text) WHERE doc_id<>hub) SELECT u, v FROM p UNION ALL SELECT v, u FROM p",
        "graph_profile": f"WITH {COPURCHASE}, h2 AS (SELECT u, v FROM cop UNION SELECT a.u, b.v FROM cop a JOIN cop b ON a.v=b.u WHERE a.u<>b.v), s AS (SELECT (SELECT count(DISTINCT u) FROM cop) nodes, (SELECT count(*) FROM cop) arcs) SELECT nodes, arcs, {r6('arcs/nodes')} avg_degree, 1 hops, (SELECT count(*) FROM cop) pairs FROM s UNION ALL SELECT nodes, arcs, {r6('arcs/nodes')}, 2, (SELECT count(*) FROM h2) FROM s",
        "symmetrize": f"WITH {SUCCESSION} SELECT u, v FROM suc UNION SELECT v, u FROM suc",
        "project_graph": f"WITH {SUCCESSION}, {POSTS}, us AS (SELECT DISTINCT user_id FROM posts WHERE topic=7) SELECT u, v FROM suc WHERE u IN (SELECT user_id FROM us) AND v IN (SELECT user_id FROM us)",
        "assign_ic": f"WITH {base} SELECT u, v, p FROM e",
        "assign_wc": f"WITH {base} SELECT u, v, {r6('w')} p FROM e",
        "assign_lt": f"WITH {base} SELECT u, v, {r6('w')} w, {r6(u01('theta', 1, 'v'))} theta FROM e",
        "opinions_uniform": f"WITH {base} SELECT id, {r6('o')} o FROM n",
        "opinions_normal": f"WITH {base}, z AS (SELECT id, sqrt(-2*ln(1-{u01('n1', 1, 'id')}))*cos(2*pi()*{u01('n2', 1, 'id')}) o FROM n) SELECT id, {r6('greatest(-1,least(1,o))')} o FROM z",
        "interactions_uniform": f"WITH {base} SELECT u, v, {r6('phi')} phi FROM e",
        "walk_score_l1": walk(1),
        "walk_score_l3": walk(3),
        "walk_score_l5": walk(5),
        "walk_score_wc": walk(3, "1.0::DOUBLE/d"),
        "walk_score_lt": walk(3, "1.0::DOUBLE/d"),
        "walk_score_profile": f"WITH {base}, {walk_rounds(3)} " + " UNION ALL ".join(f"SELECT n.id, {i} l, {r6('coalesce(score,0)')} score FROM n LEFT JOIN s{i} s ON n.id=s.id" for i in (1, 2, 3)),
        "opinion_walk_score_l1": opinion_walk(1),
        "opinion_walk_score_l3": opinion_walk(3),
        "union_walk_score_l2": union_walk(2),
        "union_walk_score_l3": union_walk(3),
        "walk_counts": counts(2),
        "simple_path_score": f"WITH {base}, {paths(3)}, z AS (SELECT src id, sum(x) score FROM sp GROUP BY 1) SELECT n.id, {r6('coalesce(score,0)')} score FROM n LEFT JOIN z USING (id)",
        "opinion_path_score_lam0": opinion_paths(2, 0.0),
        "opinion_path_score_lam1": opinion_paths(2, 1.0),
        "score_topk": f"WITH {base}, {walk_rounds(3)} SELECT CAST(row_number() OVER (ORDER BY score DESC, id) AS INTEGER) rank, id, {r6('score')} score FROM s3 ORDER BY score DESC, id LIMIT 10",
        "rescore_delta": f"WITH {base}, {walk_rounds(3)}, b AS MATERIALIZED (SELECT id FROM s3 ORDER BY score DESC, id LIMIT 1), e2 AS (SELECT * FROM e WHERE u NOT IN (SELECT id FROM b) AND v NOT IN (SELECT id FROM b)), {walk_rounds(3, 'e2', 't')} SELECT n.id, {r6('coalesce(score,0)')} score FROM n LEFT JOIN t3 t ON t.id=n.id WHERE n.id NOT IN (SELECT id FROM b)",
        "walk_score_live_edge": f"WITH {base}, {kept_live(8)}, q AS (SELECT world, u id, count(*)::DOUBLE score FROM live GROUP BY 1, 2), q2 AS (SELECT l.world, l.u id, sum(1+coalesce(score,0)) score FROM live l LEFT JOIN q ON q.world=l.world AND q.id=l.v GROUP BY 1, 2), z AS (SELECT id, sum(score)/8 score FROM q2 GROUP BY 1) SELECT n.id, {r6('coalesce(score,0)')} score FROM n LEFT JOIN z USING (id)",
        "cascade_ic": f"WITH {base}, {TOP_DEGREE}, {cascade_ic(8)} SELECT world, id, step FROM act",
        "cascade_wc": f"WITH {graph_ctes('1.0::DOUBLE/d')}, {TOP_DEGREE}, {cascade_ic(8)} SELECT world, id, step FROM act",
        "cascade_oi_ic": f"{ic} {ACT}",
        "cascade_oc_ic": f"WITH {base}, {TOP_DEGREE}, {cascade_ic(8, STEPS, 1, False)} {ACT}",
        "cascade_lt": f"WITH {base}, {TOP_DEGREE}, {cascade_lt(8)} SELECT world, id, step FROM act",
        "cascade_oi_lt": f"WITH {base}, {TOP_DEGREE}, {cascade_lt(8)} {ACT}",
        "cascade_oc": f"WITH {base}, {TOP_DEGREE}, {cascade_lt(8, STEPS, 1, False)} {ACT}",
        "live_edges": f"WITH {base}, {kept_live(4)} SELECT * FROM live",
        "sample_worlds": f"WITH {base}, {kept_ic(4)} SELECT * FROM kept",
        "cascade_live_edge": f"WITH RECURSIVE {base}, {TOP_DEGREE}, {kept_live(8)}, {reach(8, 'seeds', 'live')} SELECT DISTINCT world, id FROM rch",
        "reach_bits": f"WITH RECURSIVE {base}, {TOP_DEGREE}, {kept_ic(64)}, {reach(64, 'seeds', 'kept')} SELECT id, CAST(count(DISTINCT world) AS BIGINT) worlds FROM rch GROUP BY id",
        "activation_probability": f"{ic} SELECT id, {r6('count(*)/8::DOUBLE')} probability FROM act GROUP BY id",
        "expected_spread": f"{ic} SELECT {r6('count(*) FILTER (WHERE step>0)/8::DOUBLE')} spread FROM act",
        "opinion_spread": f"{ic} SELECT world, {r6('sum(CASE WHEN step>0 THEN o_final ELSE 0 END)')} spread FROM act GROUP BY world",
        "marginal_gain": f"WITH RECURSIVE {base}, {TOP_DEGREE}, {kept_ic(8)}, {reach(8, 'seeds', 'kept')}, a AS MATERIALIZED (SELECT min(id) id FROM seeds), b AS (SELECT count(*) FILTER (WHERE id<>src)/8::DOUBLE v FROM rch WHERE src IN (SELECT id FROM a)), t AS (SELECT x.id c, count(DISTINCT (r.world, r.id)) FILTER (WHERE r.id<>x.id AND r.id NOT IN (SELECT id FROM a))/8::DOUBLE v FROM seeds x, rch r WHERE x.id NOT IN (SELECT id FROM a) AND (r.src=x.id OR r.src IN (SELECT id FROM a)) GROUP BY 1) SELECT c id, {r6('v-(SELECT v FROM b)')} gain FROM t",
        "exact_spread_toy": f"WITH RECURSIVE {TOY}, {EXACT_TOY} SELECT * FROM toy_spread",
        "exact_opinion_spread_toy": exact_opinion_toy(),
        "score_greedy_k3_seed": greedy_by_score(3, 3, False),
        "score_greedy_k3_majority": greedy_by_score(3, 3, False, 8),
        "opinion_score_greedy_k3": greedy_by_score(3, 3, True),
        "score_greedy_k3_delta": greedy_by_score(3, 3, False),
        "mc_greedy_k2": mc_greedy(8),
        "lazy_greedy_k2": mc_greedy(8),
        "opinion_mc_greedy_k2": opinion_greedy(8, False, True),
        "oc_greedy_k2": opinion_greedy(8, True, False),
        "rr_cover_k3": rr_cover(200, 3),
        "influence_rank": f"WITH {base}, {rank_rounds(5, 0.7)} SELECT id, {r6('score')} score FROM k5",
        "degree_seeds": f"WITH {base} SELECT CAST(row_number() OVER (ORDER BY count(*) DESC, u) AS INTEGER) rank, u id, count(*)::DOUBLE score FROM e GROUP BY u ORDER BY 1 LIMIT 5",
        "random_seeds": f"WITH {base} SELECT CAST(row_number() OVER (ORDER BY {u01('pick', 1, 'id')} DESC, id) AS INTEGER) rank, id, {r6(u01('pick', 1, 'id'))} score FROM n ORDER BY 1 LIMIT 5",
        "path_mass": f"WITH {base}, {paths(2)} SELECT src u, dst v, {r6('sum(x)')} mass, CAST(count(*) AS BIGINT) paths FROM sp GROUP BY 1, 2",
        "contribution": f"WITH {base}, {paths(2)} SELECT src u, dst v, {r6('sum(x)')} summed, {r6('1-product(1-x)')} united FROM sp GROUP BY 1, 2",
        "dag_bounds": f"WITH {DAG}, e AS (SELECT u, v, 0.1::DOUBLE p FROM dag), {paths(2)}, m AS (SELECT src, dst, sum(x) s, sum(x*x) q FROM sp GROUP BY 1, 2) SELECT src id, {r6('abs(-0.9::DOUBLE*sum(s))')} union_bound, {r6('sum((s*s-q)/2)')} walk_bound, {r6('abs(-0.8::DOUBLE*sum(s))')} total_bound FROM m GROUP BY 1",
        "cycle_error": f"WITH {base}, {paths(2)} SELECT src id, {r6('sum(x*e.p/(length+1))')} error FROM sp JOIN e ON e.u=dst AND e.v=src GROUP BY 1",
        "expected_path_mass": f"WITH g AS (SELECT count(o_custkey)/count(DISTINCT o_custkey)::DOUBLE eta FROM orders) SELECT i, {r6('eta**(i-1)*0.1::DOUBLE**i')} mass, {r6('eta**(i-1)*0.1::DOUBLE**i/i')} cycle_mass, {r6('eta*0.1::DOUBLE')} critical FROM g, (SELECT range i FROM range(1, 9)) WHERE eta IS NOT NULL",
        "order_condition": f"WITH RECURSIVE {TOY}, {EXACT_TOY}, {walk_rounds(3, 'arcs')}, r AS (SELECT t.id, t.spread t, coalesce(score,0) s, coalesce(score,0)-t.spread x FROM toy_spread t LEFT JOIN s3 ON s3.id=t.id) SELECT a.id u, b.id v, b.x-a.x<a.t-b.t holds, a.s>b.s kept FROM r a JOIN r b ON a.t>b.t",
        "submodularity_two_layer": "WITH c AS (SELECT o_custkey, count(*) n, row_number() OVER (ORDER BY o_custkey) a, row_number() OVER (ORDER BY o_custkey DESC) z FROM orders WHERE o_custkey IS NOT NULL GROUP BY 1), seeds AS (SELECT 1::BIGINT k, n/2 x FROM c WHERE a=1 UNION ALL SELECT 2, -n/2 FROM c WHERE z=1 UNION ALL SELECT 3, n/2 FROM c WHERE a=2) SELECT k size, round(sum(x) OVER (ORDER BY k),6)+0.0 spread FROM seeds",
        "set_cover_instance": "WITH sets(kind, i, j) AS (VALUES ('cover',1,0),('cover',1,1),('cover',2,2),('cover',2,3),('cover',3,1),('cover',3,2),('none',1,0),('none',1,1),('none',2,1),('none',2,2),('none',3,0),('none',3,2)), pairs AS (SELECT DISTINCT a.kind, a.i x, b.i y FROM sets a JOIN sets b ON a.kind=b.kind AND a.i<b.i), c AS (SELECT p.kind, x, y, count(DISTINCT j) covered FROM pairs p JOIN sets s ON s.kind=p.kind AND s.i IN (x, y) GROUP BY ALL), o AS (SELECT 4.0::DOUBLE n, 5 middle, (1/4.0::DOUBLE)/2 element), z AS (SELECT kind, covered*element+middle*(-1/(2*n)+element)/2+(-1+1/n+(-1/(2*n)+element)/2)/2 spread FROM c, o) SELECT kind, round(max(spread),6)+0.0 spread FROM z GROUP BY kind",
        "submodularity_violations": "WITH s AS (SELECT range m FROM range(16)), v AS (SELECT m, list_sum([CASE WHEN (m>>i)&1=0 THEN 0.0::DOUBLE WHEN i=3 THEN -1.0 ELSE 1.0 END FOR i IN range(4)]) spread FROM s), g AS (SELECT a.m, i x, b.spread-a.spread gain FROM v a, range(4) r(i), v b WHERE (a.m>>i)&1=0 AND b.m=a.m+(1<<i)) SELECT 'monotone' kind, CAST(count(*) AS BIGINT) n FROM g WHERE round(gain,9)<0 UNION ALL SELECT 'submodular', CAST(count(*) AS BIGINT) FROM g a JOIN g b ON a.x=b.x AND (a.m&b.m)=a.m AND a.m<>b.m WHERE round(b.gain-a.gain,9)>0",
        "repeated_paths": f"WITH {PATH_COUNTS} SELECT t, {r6('1-(1-0.125::DOUBLE)**t')} united, {r6('t*0.125::DOUBLE')} summed FROM pc",
        "violation_window": f"WITH {PATH_COUNTS} SELECT a.t t1, b.t t2, {r6('ln(a.t/b.t::DOUBLE)/-ln(0.1::DOUBLE)')} gap FROM pc a JOIN pc b ON a.t>b.t",
        "set_decomposition": f"WITH RECURSIVE {base}, {TOP_DEGREE}, {kept_ic(8)}, {reach(8, 'seeds', 'kept')}, f AS MATERIALIZED (SELECT min(id) id FROM seeds), a AS MATERIALIZED (SELECT DISTINCT world, id FROM rch WHERE src IN (SELECT id FROM f)), b AS MATERIALIZED (SELECT DISTINCT world, id FROM rch WHERE src NOT IN (SELECT id FROM f)) SELECT w.world, (SELECT count(*) FROM (SELECT id FROM a WHERE a.world=w.world UNION SELECT id FROM b WHERE b.world=w.world)) n_union, (SELECT count(*) FROM a WHERE a.world=w.world) n_a, (SELECT count(*) FROM b WHERE b.world=w.world AND b.id NOT IN (SELECT id FROM a WHERE a.world=w.world)) n_rest FROM (SELECT DISTINCT world FROM rch) w",
        "lt_equals_live_edge": f"WITH RECURSIVE {base}, {TOP_DEGREE}, {kept_live(64)}, {reach(64, 'seeds', 'live')}, {cascade_lt(64)} SELECT 'live edges' model, {r6('(SELECT count(*) FROM (SELECT DISTINCT world, id FROM rch) WHERE id NOT IN (SELECT id FROM seeds))/64::DOUBLE')} spread UNION ALL SELECT 'thresholds', {r6('(SELECT count(*) FROM act WHERE step>0)/64::DOUBLE')}",
        "dag_lt_exactness": f"WITH {DAG}, deg AS (SELECT v, count(*) d FROM dag GROUP BY v), e AS (SELECT u, v, 1.0::DOUBLE/d p FROM dag JOIN deg USING (v)), {paths(2)} SELECT src id, {r6('sum(x)')} score FROM sp GROUP BY 1",
        "path_closed_form": PATHS,
        "opinion_walk_score_normal": f"WITH {base}, nn AS (SELECT id, greatest(-1,least(1,sqrt(-2*ln(1-{u01('n1', 1, 'id')}))*cos(2*pi()*{u01('n2', 1, 'id')}))) o FROM n), {opinion_rounds(3, 'e', 'nn')} SELECT id, {r6('score')} score FROM q3",
        "cascade_oi_wc": f"WITH {graph_ctes('1.0::DOUBLE/d')}, {TOP_DEGREE}, {cascade_ic(8)} {ACT}",
        "spread_stderr": f"{ic}, x AS (SELECT world, count(*) FILTER (WHERE step>0) c FROM act GROUP BY world) SELECT {r6('avg(c)')} spread, {r6('stddev_samp(c)/sqrt(8)')} stderr FROM x",
        "graph_normalize": f"WITH {base} SELECT u, v, p, {r6('w')} w, {r6('phi')} phi FROM e",
        "graph_violations": f"WITH {base} SELECT 'self_loop' rule, CAST(count(*) AS BIGINT) n FROM e WHERE u=v UNION ALL SELECT 'null', count(*) FROM e WHERE u IS NULL OR v IS NULL OR p IS NULL UNION ALL SELECT 'range', count(*) FROM e WHERE p<0 OR p>1 OR w<0 OR w>1 OR phi<0 OR phi>1 UNION ALL SELECT 'opinion', count(*) FROM n WHERE o IS NULL OR o<-1 OR o>1 UNION ALL SELECT 'repeated', count(*) FROM (SELECT 1 FROM e GROUP BY u, v HAVING count(*)>1) UNION ALL SELECT 'unknown_end', count(*) FROM (SELECT u id FROM e UNION ALL SELECT v FROM e) x WHERE id NOT IN (SELECT id FROM n)",
        "brute_force_toy": f"WITH RECURSIVE {TOY}, kept AS MATERIALIZED (SELECT CAST(range AS INTEGER) world, u::BIGINT u, v::BIGINT v FROM range(64), arcs WHERE {u01('ic', 1, 'range', 'u', 'v')}<p), {reach(64, 'nodes', 'kept')}, pr AS (SELECT a.id x, b.id y FROM nodes a JOIN nodes b ON a.id<b.id), z AS (SELECT x, y, count(DISTINCT (world, rch.id))/64::DOUBLE-2 s FROM pr JOIN rch ON src IN (x, y) GROUP BY 1, 2), best AS (SELECT * FROM z ORDER BY round(s,9) DESC, x, y LIMIT 1) SELECT 1 rank, x id, {r6('s')} score FROM best UNION ALL SELECT 2, y, {r6('s')} FROM best",
        "opinion_error_split": f"WITH {TOPIC_EDGES}, {ESTIMATE}, who AS (SELECT DISTINCT topic, user_id FROM org), k AS (SELECT est.*, CASE WHEN who.user_id IS NULL THEN 'other' ELSE 'seed' END node FROM est LEFT JOIN who USING (topic, user_id)) SELECT node, {r6('sqrt(avg((estimate-truth)**2))/(max(truth)-min(truth))')} nrmse, CAST(count(*) AS BIGINT) n FROM k GROUP BY node",
        "rank_agreement": f"WITH {graph_ctes(source='suc')}, {walk_rounds(3)}, j AS (SELECT id, round(a.score,9) a, round(b.score,9) b FROM s1 a JOIN s3 b USING (id)), z AS (SELECT sign(x.a-y.a)*sign(x.b-y.b) s FROM j x JOIN j y ON x.id<y.id) SELECT CAST(sum((s>0)::INT) AS BIGINT) concordant, CAST(sum((s<0)::INT) AS BIGINT) discordant, {r6('avg(s)')} tau FROM z",
        "topic_posts": f"WITH {POSTS} SELECT topic, CAST(count(*) AS BIGINT) posts, {r6('avg(opinion)')} opinion FROM posts GROUP BY 1",
        "gap_threshold": f"WITH {POSTS} SELECT topic, (round(threshold,3)+0.0) threshold FROM lim",
        "topic_epochs_post": f"WITH {POSTS} SELECT topic, epoch, CAST(count(*) AS BIGINT) posts FROM ep GROUP BY 1, 2",
        "topic_epochs_seed": SEED_EPOCHS,
        "topic_edges": f"WITH {TOPIC_EDGES} SELECT * FROM te",
        "originators": f"WITH {TOPIC_EDGES} SELECT * FROM org",
        "top_topics": f"WITH {POSTS} SELECT topic, CAST(count(*) AS BIGINT) posts FROM posts GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10",
        "post_opinion": f"WITH {POSTS} SELECT event_id, {r8('opinion')} opinion FROM posts",
        "true_opinion": f"WITH {POSTS} SELECT topic, user_id, {r8('avg(opinion)')} opinion FROM posts GROUP BY 1, 2",
        "estimated_opinion": f"WITH {POSTS}, {ESTIMATE} SELECT topic, user_id, {r8('truth')} truth, {r8('estimate')} estimate FROM est",
        "estimated_interaction": f"WITH {TOPIC_EDGES}, ag AS (SELECT te.u, te.v, avg((sign(a.opinion)=sign(b.opinion))::INT) phi, count(*) times FROM te JOIN mem a ON a.topic=te.topic AND a.epoch=te.epoch AND a.user_id=te.u JOIN mem b ON b.topic=te.topic AND b.epoch=te.epoch AND b.user_id=te.v GROUP BY 1, 2) SELECT u, v, {r6('coalesce(phi,0.5)')} phi, CAST(coalesce(times,0) AS BIGINT) times FROM suc LEFT JOIN ag USING (u, v)",
        "opinion_error": f"WITH {POSTS}, {ESTIMATE} SELECT topic, {r6('sqrt(avg((estimate-truth)**2))/(max(truth)-min(truth))')} nrmse, CAST(count(*) AS BIGINT) n FROM est GROUP BY topic HAVING max(truth)>min(truth)",
        "ground_truth_spread": f"WITH {TOPIC_EDGES} SELECT m.topic, m.epoch, {r6('sum(CASE WHEN o.user_id IS NULL THEN opinion ELSE 0 END)')} spread FROM mem m LEFT JOIN org o ON o.topic=m.topic AND o.epoch=m.epoch AND o.user_id=m.user_id GROUP BY 1, 2",
        "churn_labels": f"WITH {LABELS} SELECT id, label FROM lab",
        "balanced_sample": f"WITH {LABELS}, r AS (SELECT id, label, row_number() OVER (PARTITION BY label ORDER BY {u01('bal', 1, 'id')}, id) k FROM lab) SELECT id, label FROM r WHERE k<=(SELECT min(c) FROM (SELECT count(*) c FROM lab GROUP BY label))",
        "label_propagation_t5": f"WITH {SIMILARITY}, {LABELS}, {propagation(5)} SELECT id, {r6('val')} \"value\" FROM v5",
        "tree_exactness": f"WITH {TREE}, e AS (SELECT u, v, 0.1::DOUBLE p FROM tree), {walk_rounds(3)} SELECT id, {r6('score')} score FROM s3",
    }
    for name, lam in (("0", 0.0), ("05", 0.5), ("1", 1.0)):
        out[f"effective_spread_lam{name}"] = f"{ic} SELECT {r6(f'sum(CASE WHEN step=0 THEN 0 WHEN o_final<0 THEN {lam}::DOUBLE*o_final ELSE o_final END)/8')} spread FROM act"
    return out
