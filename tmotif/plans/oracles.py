"""SQL that says the same as the queries, for another engine: self-joins, counts by range joins, repeated draws."""

from __future__ import annotations

from tmotif.functions.motif import EIGHT, Anchor, Motif, PathClass, WedgeClass, motif

DAY, HOUR = 86_400_000_000, 3_600_000_000
R_DELTA, F_DELTA, T_DELTA, N_DELTA = DAY, 4 * HOUR, 30, 3
K = 5_000

TOPIC = r"""CAST(regexp_extract(props, '"k":\s*(\d+)', 1) AS INT)"""
PREVIOUS = f"SELECT *, lag(user_id) OVER (PARTITION BY {TOPIC} ORDER BY ts, event_id) AS previous FROM events"
LINES = "SELECT *, l_orderkey * 1000 + row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate) AS line_id FROM lineitem"
DAYS = "date_diff('day', DATE '1970-01-01', CAST({} AS DATE))"


def reply(fold: int | None = None, loops: bool = False) -> str:
    mod = f" % {fold}" if fold else ""
    return f"SELECT CAST(event_id AS BIGINT) AS eid, CAST(user_id{mod} AS BIGINT) AS src, CAST(previous{mod} AS BIGINT) AS dst, CAST(epoch_us(ts) AS BIGINT) AS t, event_type AS label FROM ({PREVIOUS}) WHERE previous IS NOT NULL" + ("" if loops else f" AND user_id{mod} <> previous{mod}")


NATION = f"""SELECT CAST(line_id AS BIGINT) AS eid, CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst, CAST({DAYS.format('l_shipdate')} AS BIGINT) AS t
FROM ({LINES}) JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey WHERE c_nationkey <> s_nationkey"""
TRADE = f"""SELECT CAST(line_id * 2 AS BIGINT) AS eid, CAST(o_custkey * 2 AS BIGINT) AS src, CAST(l_suppkey * 2 + 1 AS BIGINT) AS dst, CAST({DAYS.format('o_orderdate')} AS BIGINT) AS t, 'order' AS label
FROM ({LINES}) JOIN orders ON o_orderkey = l_orderkey
UNION ALL SELECT CAST(line_id * 2 + 1 AS BIGINT), CAST(l_suppkey * 2 + 1 AS BIGINT), CAST(o_custkey * 2 AS BIGINT), CAST({DAYS.format('l_shipdate')} AS BIGINT), 'ship' FROM ({LINES}) JOIN orders ON o_orderkey = l_orderkey"""
VIEWS = {"R": reply(), "F": reply(6), "N": NATION, "T": TRADE}


def view(name: str, *more: str) -> str:
    return "WITH edges AS MATERIALIZED (" + VIEWS[name] + ")" + "".join(f",\n{m}" for m in more) + "\n"


def self_join(m: Motif, delta: int, given: dict[int, str] | None = None) -> tuple[str, str]:
    """FROM and WHERE over aliases e0, e1, ..: all matches."""
    bound: dict[str, str] = {}
    tables, tests = [], []
    for p, (a, b) in enumerate(m.edges):
        tables.append(f"edges e{p}")
        for x, end in ((a, "src"), (b, "dst")):
            if x in bound:
                tests.append(f"e{p}.{end} = {bound[x]}")
            else:
                tests += [f"e{p}.{end} <> {y}" for y in bound.values()]
                bound[x] = f"e{p}.{end}"
        if p:
            tests += [f"e{p}.t > e{p - 1}.t", f"e{p}.t <= e0.t + {delta}"]
    return ", ".join(tables), " AND ".join(tests)


def stepwise(m: Motif, delta: int, tag: str = "g", edges: str = "edges") -> tuple[list[str], str]:
    """CTEs, one a pattern edge, of partial matches folded by what the next edges ask of them; and the count of all matches."""
    bound: list[str] = []
    parts = []
    for p, (a, b) in enumerate(m.edges):
        ends = {a: "e.src", b: "e.dst"}
        new = [x for x in (a, b) if x not in bound]
        every = [*(f"g.v_{x}" for x in bound), *(f"{ends[x]} AS v_{x}" for x in new)]
        if p == 0:
            parts.append(f"{tag}0 AS MATERIALIZED (SELECT {', '.join(every)}, e.t AS early, e.t AS late, count(*) AS times FROM {edges} e GROUP BY ALL)")
        else:
            tests = [f"{ends[x]} = g.v_{x}" for x in (a, b) if x in bound] + [f"{ends[x]} <> g.v_{y}" for x in new for y in bound]
            tests += ["e.t > g.late", f"e.t <= g.early + {delta}"]
            parts.append(f"{tag}{p} AS MATERIALIZED (SELECT {', '.join(every)}, g.early, e.t AS late, sum(g.times) AS times FROM {tag}{p - 1} g JOIN {edges} e ON {' AND '.join(tests)} GROUP BY ALL)")
        bound += new
    return parts, f"(SELECT CAST(coalesce(sum(times), 0) AS BIGINT) FROM {tag}{len(m.edges) - 1})"


def counts(view_name: str, names, delta: int, select: str = "SELECT '{name}' AS motif, CAST({delta} AS BIGINT) AS delta, {count} AS count") -> str:
    """A row for each motif."""
    parts, rows = [], []
    for k, name in enumerate(names):
        own, count = stepwise(motif(name), delta, f"g{k}_")
        parts += own
        rows.append(select.format(name=motif(name).name, delta=delta, count=count))
    return view(view_name, *parts) + " UNION ALL ".join(rows)


def exact(view_name: str, name: str, delta: int) -> str:
    return counts(view_name, [name], delta)


def side(alias: str, t: str, b: str, delta: int) -> str:
    return f"{alias}.t >= {t} - {delta} AND {alias}.t < {t}" if b == "<" else f"{alias}.t > {t} AND {alias}.t <= {t} + {delta}"


def degree(number: str, end: str, a: str, b: str, delta: int, static: bool = False) -> str:
    """CTE d<number>: eid, lo, n."""
    own = "src" if a == "+" else "dst"
    low = f"f.t < e.t - {delta}" if b == "<" else "f.t <= e.t"
    inside = side("f", "e.t", b, delta)
    if static:
        low, inside = "false", "true"
    return f"d{number} AS MATERIALIZED (SELECT e.eid, CAST(count(*) FILTER ({low}) AS BIGINT) AS lo, CAST(count(*) FILTER ({inside}) AS BIGINT) AS n FROM edges e LEFT JOIN edges f ON f.{own} = e.{end} GROUP BY e.eid)"


def weighted(cls: PathClass | WedgeClass, delta: int, static: bool = False) -> list[str]:
    """CTEs up to weighted: eid, src, dst, t, lo1, n1(, lo3, n3), w."""
    if isinstance(cls, PathClass):
        return [degree("1", "src", cls.a1, cls.b1, delta, static), degree("3", "dst", cls.a3, cls.b3, delta, static), "weighted AS MATERIALIZED (SELECT e.eid, e.src, e.dst, e.t, d1.lo AS lo1, d1.n AS n1, d3.lo AS lo3, d3.n AS n3, d1.n * d3.n AS w FROM edges e JOIN d1 USING (eid) JOIN d3 USING (eid))"]
    return [degree("1", cls.pivot, cls.a, cls.b, delta, static), "weighted AS MATERIALIZED (SELECT e.eid, e.src, e.dst, e.t, d1.lo AS lo1, d1.n AS n1, d1.n AS w FROM edges e JOIN d1 USING (eid))"]


LISTS = "lists AS MATERIALIZED (SELECT dir, vertex, CAST(row_number() OVER (PARTITION BY dir, vertex ORDER BY t, eid) - 1 AS BIGINT) AS rank, t, eid, other FROM (SELECT '+' AS dir, src AS vertex, dst AS other, t, eid FROM edges UNION ALL SELECT '-', dst, src, t, eid FROM edges))"
OFFSETS = "centers AS MATERIALIZED (SELECT *, sum(w) OVER (ORDER BY t, eid) - w AS first FROM weighted WHERE w > 0)"


WHOLE = "(SELECT coalesce(sum(w), 0) FROM weighted)"


def hashed(text: str) -> str:
    return f"CAST(CAST('0x' || substr(md5({text}), 1, 13) AS BIGINT) AS HUGEINT)"


def draws(k: int, seed: int = 42, total: str = WHOLE) -> str:
    return f"drawn AS MATERIALIZED (SELECT i AS draw, ({hashed(f"'{seed}|' || i")} * CAST({total} AS HUGEINT)) // 4503599627370496 AS path_id FROM range({k}) r(i))"


def draws_of_seeds(k: int, seeds, total: str = WHOLE) -> str:
    """Draw i of the n-th seed is n * k + i."""
    rows = ", ".join(f"({n}, '{s}|')" for n, s in enumerate(seeds))
    return f"drawn AS MATERIALIZED (SELECT n * {k} + i AS draw, ({hashed('name || i')} * CAST({total} AS HUGEINT)) // 4503599627370496 AS path_id FROM range({k}) r(i), (VALUES {rows}) s(n, name))"


def draws_stratified(k: int, seed: int = 42, total: str = WHOLE) -> str:
    low, high = f"CAST({total} AS HUGEINT) * i // {k}", f"CAST({total} AS HUGEINT) * (i + 1) // {k}"
    return f"drawn AS MATERIALIZED (SELECT i AS draw, {low} + {hashed(f"'{seed}|' || i")} * greatest({high} - {low}, 1) // 4503599627370496 AS path_id FROM range({k}) r(i))"


def draws_distinct(k: int, seed: int = 42) -> list[str]:
    return [draws(k, seed).replace("drawn AS", "repeated AS", 1), "drawn AS MATERIALIZED (SELECT min(draw) AS draw, path_id FROM repeated GROUP BY path_id)"]


def located_poisson(k: int, seed: int = 42) -> str:
    rate = f"(CAST(c.w AS DOUBLE) * {k} / {WHOLE})"
    u = f"CAST({hashed(f"'{seed}|' || c.eid")} AS DOUBLE) / 4503599627370496"
    times = f"CAST(floor({rate}) AS BIGINT) + CASE WHEN {u} < {rate} - floor({rate}) THEN 1 ELSE 0 END"
    return f"SELECT row_number() OVER () AS draw, c.first + o AS path_id, * FROM (SELECT c.*, {hashed(f"'{seed}|' || c.eid || '|' || nth")} * c.w // 4503599627370496 AS o FROM centers c, unnest(range(1, {times} + 1)) x(nth)) c"


def decoded(cls: PathClass | WedgeClass, located: str = "SELECT draw, path_id, c.*, path_id - c.first AS o FROM drawn ASOF JOIN centers c ON path_id >= c.first") -> list[str]:
    if isinstance(cls, PathClass):
        return [f"located AS MATERIALIZED ({located})", f"""paths AS MATERIALIZED (SELECT CAST(draw AS BIGINT) AS draw, CAST(path_id AS BIGINT) AS path_id, a.eid AS eid1, l.eid AS eid2, b.eid AS eid3, a.t AS t1, l.t AS t2, b.t AS t3, a.other AS v0, l.src AS v1, l.dst AS v2, b.other AS v3
FROM located l JOIN lists a ON a.dir = '{cls.a1}' AND a.vertex = l.src AND a.rank = l.lo1 + l.o // l.n3 JOIN lists b ON b.dir = '{cls.a3}' AND b.vertex = l.dst AND b.rank = l.lo3 + l.o % l.n3)"""]
    return [f"located AS MATERIALIZED ({located})", f"""paths AS MATERIALIZED (SELECT CAST(draw AS BIGINT) AS draw, CAST(path_id AS BIGINT) AS path_id, l.eid AS eid1, a.eid AS eid2, l.t AS t1, a.t AS t2, l.src AS v0, l.dst AS v1, a.other AS v2
FROM located l JOIN lists a ON a.dir = '{cls.a}' AND a.vertex = l.{cls.pivot} AND a.rank = l.lo1 + l.o)"""]


def valid(anchor: Anchor, delta: int) -> str:
    n = len(anchor.vertices)
    tests = [f"v{i} <> v{j}" for i in range(n) for j in range(i)]
    times = [f"t{k}" for _, k in sorted((p, k) for k, p in enumerate(anchor.positions, 1))]
    tests += [f"{a} < {b}" for a, b in zip(times, times[1:], strict=False)]
    return " AND ".join([*tests, f"{times[-1]} - {times[0]} <= {delta}"])


def completed(m: Motif, anchor: Anchor, delta: int) -> list[str]:
    """CTE done: draw, x; for each valid path with completions. One CTE a pattern edge, folded by (draw, time of the last edge)."""
    times = {p: f"p.t{k}" for k, p in enumerate(anchor.positions, 1)}
    where = {v: f"p.v{k}" for k, v in enumerate(anchor.vertices)}
    parts = [f"ok AS MATERIALIZED (SELECT * FROM paths WHERE {valid(anchor, delta)})", f"c0 AS (SELECT p.draw, {times[0]} AS late, 1 AS x FROM ok p)"]
    for q, (a, b) in enumerate(m.edges[1:], 1):
        if q in times:
            parts.append(f"c{q} AS MATERIALIZED (SELECT c.draw, {times[q]} AS late, sum(c.x) AS x FROM c{q - 1} c JOIN ok p USING (draw) WHERE {times[q]} > c.late GROUP BY ALL)")
            continue
        later = [t for s, t in times.items() if s > q]
        tests = [f"e.src = {where[a]}", f"e.dst = {where[b]}", "e.t > c.late", f"e.t <= {times[0]} + {delta}", *(f"e.t < {t}" for t in later)]
        parts.append(f"c{q} AS MATERIALIZED (SELECT c.draw, e.t AS late, sum(c.x) AS x FROM c{q - 1} c JOIN ok p USING (draw) JOIN edges e ON {' AND '.join(tests)} GROUP BY ALL)")
    return [*parts, f"done AS MATERIALIZED (SELECT draw, CAST(sum(x) AS BIGINT) AS x FROM c{len(m.edges) - 1} GROUP BY draw)"]


ESTIMATE = "SELECT '{name}' AS motif, CAST({delta} AS BIGINT) AS delta, CAST({k} AS BIGINT) AS k, CAST((SELECT coalesce(sum(w), 0) FROM weighted) AS BIGINT) AS w_total, CAST(coalesce((SELECT sum(x) FROM done), 0) AS BIGINT) AS cnt, CAST(coalesce((SELECT sum(x) FROM done), 0) AS DOUBLE) / CAST({k} AS DOUBLE) * CAST((SELECT coalesce(sum(w), 0) FROM weighted) AS DOUBLE) AS estimate"


def sampled(view_name: str, name: str, delta: int, k: int = K, seed: int = 42, static: bool = False, drawn: list[str] | None = None) -> list[str]:
    m = motif(name)
    a = m.anchor()
    return [*weighted(a.cls, delta, static), LISTS, OFFSETS, *(drawn or [draws(k, seed)]), *decoded(a.cls), *completed(m, a, delta)]


def constrained(name: str, delta: int, k: int = K, seed: int = 42) -> list[str]:
    """CTEs for an anchor of the first three edges whose ends lie before and after the center: w and all up to done."""
    m = motif(name)
    a = m.anchor()
    return [
        f"weighted AS MATERIALIZED (SELECT e.eid, e.src, e.dst, e.t, a.eid AS eid1, a.t AS t1, a.src AS v0, count(b.eid) AS w FROM edges e JOIN edges a ON a.dst = e.src AND a.t >= e.t - {delta} AND a.t < e.t JOIN edges b ON b.src = e.dst AND b.t > e.t AND b.t <= a.t + {delta} GROUP BY ALL)",
        LISTS,
        "centers AS MATERIALIZED (SELECT *, sum(w) OVER (ORDER BY t, eid, eid1) - w AS first FROM weighted)",
        draws(k, seed),
        "lows AS MATERIALIZED (SELECT e.eid, count(f.eid) AS lo FROM edges e LEFT JOIN edges f ON f.src = e.dst AND f.t <= e.t GROUP BY e.eid)",
        "located AS MATERIALIZED (SELECT draw, path_id, c.*, path_id - c.first AS o, l.lo FROM drawn ASOF JOIN centers c ON path_id >= c.first JOIN lows l ON l.eid = c.eid)",
        "paths AS MATERIALIZED (SELECT draw, l.eid1, l.eid AS eid2, b.eid AS eid3, l.t1, l.t AS t2, b.t AS t3, l.v0, l.src AS v1, l.dst AS v2, b.other AS v3 FROM located l JOIN lists b ON b.dir = '+' AND b.vertex = l.dst AND b.rank = l.lo + l.o)",
        *completed(m, a, delta),
    ]


def adaptive(view_name: str, name: str, delta: int, epsilon: float, first: int = 2_000, steps: int = 4) -> str:
    """The first k among first, 2 * first, .. that is precise enough, and its estimate."""
    most = first << steps - 1
    rows = " UNION ALL ".join(f"SELECT {first << n} AS k, coalesce(sum(x), 0) AS cnt, coalesce(sum(CAST(x AS DOUBLE) * x), 0) AS squares FROM done WHERE draw < {first << n}" for n in range(steps))
    each = f"CAST(cnt AS DOUBLE) / k * CAST({WHOLE} AS DOUBLE)"
    error = f"CAST({WHOLE} AS DOUBLE) * sqrt(greatest(squares / k - (CAST(cnt AS DOUBLE) / k) * (CAST(cnt AS DOUBLE) / k), 0) / k)"
    return view(view_name, *sampled(view_name, name, delta, most), f"runs AS ({rows})", f"fine AS (SELECT * FROM runs WHERE cnt > 0 AND 1.959964 * {error} <= {epsilon} * {each})") + f"SELECT '{name}' AS motif, CAST({delta} AS BIGINT) AS delta, CAST(k AS BIGINT) AS k, CAST({WHOLE} AS BIGINT) AS w_total, CAST(cnt AS BIGINT) AS cnt, {each} AS estimate FROM fine WHERE k = (SELECT min(k) FROM fine)"


def hub(name: str, delta: int, k: int = K) -> str:
    """A star of three out-edges: the base edge, and a pair of its hub's later out-edges."""
    parts = [degree("1", "src", "+", ">", delta), "weighted AS MATERIALIZED (SELECT e.eid, e.src, e.dst, e.t, d1.lo, d1.n, d1.n * d1.n AS w FROM edges e JOIN d1 USING (eid))", LISTS, OFFSETS, draws(k), "located AS MATERIALIZED (SELECT draw, c.*, path_id - c.first AS o FROM drawn ASOF JOIN centers c ON path_id >= c.first)"]
    parts.append("done AS MATERIALIZED (SELECT draw, 1 AS x FROM located l JOIN lists a ON a.dir = '+' AND a.vertex = l.src AND a.rank = l.lo + l.o // l.n JOIN lists b ON b.dir = '+' AND b.vertex = l.src AND b.rank = l.lo + l.o % l.n WHERE a.t < b.t AND a.other <> b.other AND a.other <> l.dst AND b.other <> l.dst)")
    return view("R", *parts) + ESTIMATE.format(name=name, delta=delta, k=k)


def rates(view_name: str, name: str, delta: int, k: int = K) -> str:
    tail = "SELECT '{s}' AS sampler, CAST({w} AS BIGINT) AS w_total, CAST((SELECT count(*) FROM ok) AS DOUBLE) / {k} AS valid_rate, CAST((SELECT count(*) FROM done) AS DOUBLE) / {k} AS hit_rate"
    parts = {"static": sampled(view_name, name, delta, k, static=True), "centered": sampled(view_name, name, delta, k), "constrained": constrained(name, delta, k)}
    return " UNION ALL ".join(f"({view(view_name, *p)}{tail.format(s=x, w=WHOLE, k=k)})" for x, p in parts.items())


def errors_of_seeds(view_name: str, name: str, delta: int, k: int, seeds) -> str:
    own, count = stepwise(motif(name), delta)
    runs = f"runs AS (SELECT n, CAST(coalesce((SELECT sum(x) FROM done WHERE draw // {k} = n), 0) AS DOUBLE) / {k} * CAST({WHOLE} AS DOUBLE) AS estimate FROM range({len(seeds)}) r(n))"
    parts = [*sampled(view_name, name, delta, drawn=[draws_of_seeds(k, seeds)]), *own, runs, f"truth AS (SELECT {count} AS exact)"]
    return view(view_name, *parts) + f"SELECT '{name}' AS motif, exact, CASE WHEN exact > 0 THEN round(avg(abs(estimate - exact) / exact), 6) END AS mean_error, CASE WHEN exact > 0 THEN round(stddev_samp(abs(estimate - exact) / exact), 6) ELSE 0.0 END AS std_error FROM runs, truth GROUP BY exact"


def converging(view_name: str, name: str, delta: int, ks, seeds) -> str:
    rows = []
    for k in ks:
        run = view(view_name, *sampled(view_name, name, delta, drawn=[draws_of_seeds(k, seeds)]))
        rows.append(f"({run}SELECT '{name}' AS motif, CAST({k} AS BIGINT) AS k, CAST(s.seed AS INT) AS seed, CAST(coalesce((SELECT sum(x) FROM done WHERE draw // {k} = s.n), 0) AS BIGINT) AS cnt FROM (VALUES {', '.join(f'({n}, {x})' for n, x in enumerate(seeds))}) s(n, seed))")
    return " UNION ALL ".join(rows)


def bound(name: str) -> str:
    """Draws by the bound, from the folded graph's own figures."""
    m = motif(name)
    own, count = stepwise(m, F_DELTA)
    sigma = f"(SELECT max(m) FROM (SELECT (SELECT count(*) FROM edges f WHERE f.src = e.src AND f.dst = e.dst AND f.t BETWEEN e.t AND e.t + {F_DELTA}) AS m FROM edges e))"
    return view("F", *weighted(m.anchor().cls, F_DELTA), *own, f"held AS (SELECT CAST({sigma} AS DOUBLE) AS sigma, CAST({WHOLE} AS DOUBLE) AS w, {count} AS c)") + f"SELECT '{name}' AS motif, CASE WHEN c > 0 THEN CAST(ceil(3 * power(sigma, {m.free_edges}) * w * ln(2 / 0.05) / (c * power(0.1, 2))) AS BIGINT) END AS k FROM held"


def anchors_of(view_name: str, name: str, delta: int) -> str:
    return view(view_name, *census_parts(name, delta)) + f"SELECT '{view_name}' AS graph, '{name}' AS motif, CAST(max(x) AS BIGINT) AS b_max, count(*) AS hits, CAST(coalesce(sum(x), 0) AS BIGINT) AS count, round(avg(x), 6) AS b_avg, round(stddev_pop(x), 6) AS b_std, round(coalesce(sum(x), 0) / CAST({WHOLE} AS DOUBLE), 9) AS b_avg_all FROM done"


def estimate(view_name: str, name: str, delta: int, k: int = K, seed: int = 42, static: bool = False) -> str:
    return view(view_name, *sampled(view_name, name, delta, k, seed, static)) + ESTIMATE.format(name=motif(name).name, delta=delta, k=k)


def census_parts(name: str, delta: int) -> list[str]:
    m = motif(name)
    a = m.anchor()
    every = "SELECT CAST(c.first + r.o AS BIGINT) AS draw, c.first + r.o AS path_id, c.*, r.o FROM centers c, unnest(range(CAST(c.w AS BIGINT))) r(o)"
    return [*weighted(a.cls, delta), LISTS, OFFSETS, *decoded(a.cls, every), *completed(m, a, delta)]


def union_classes(classes, delta: int, select: str) -> str:
    """One row per (class, edge): the sum of products of range counts."""
    parts = []
    for sign in "-+":
        for b in "<>":
            parts += [degree(f"u{'mp'[sign == '+']}{'ba'[b == '>']}", "src", sign, b, delta), degree(f"v{'mp'[sign == '+']}{'ba'[b == '>']}", "dst", sign, b, delta)]
    name = lambda end, a, b: f"d{end}{'mp'[a == '+']}{'ba'[b == '>']}"
    rows = []
    for c in classes:
        if isinstance(c, PathClass):
            x, y = name("u", c.a1, c.b1), name("v", c.a3, c.b3)
            rows.append(f"SELECT '{c}' AS class, x.eid, x.n * y.n AS w FROM {x} x JOIN {y} y USING (eid)")
        else:
            rows.append(f"SELECT '{c}' AS class, x.eid, x.n AS w FROM {name('u' if c.pivot == 'src' else 'v', c.a, c.b)} x")
    return view("R", *parts, "every_w AS (" + " UNION ALL ".join(rows) + ")") + select


def window_matches(name: str, delta: int, windows: str, keyed: str = "win") -> str:
    m = motif(name)
    tables, tests = self_join(m, delta)
    tables = tables.replace("edges ", "inside ")
    same = " AND ".join(f"e{p}.{keyed} = e0.{keyed}" for p in range(1, len(m.edges)))
    return f"found AS MATERIALIZED (SELECT e0.t AS t0, e{len(m.edges) - 1}.t AS t1 FROM {tables} WHERE {same} AND {tests})"


def windows(v: str, name: str, delta: int, n: int) -> tuple[str, str]:
    """Windows at uniform starts, and at uniformly drawn edges."""
    width = int(1.25 * delta)
    extent = f"(SELECT max(t) - min(t) + {width} + 1 FROM edges)"
    inside = f"inside AS MATERIALIZED (SELECT w.win, e.* FROM edges e JOIN windows w ON e.t BETWEEN w.a AND w.a + {width})"
    found = window_matches(name, delta, "")
    a = view(v, draws(n, total=extent), f"windows AS MATERIALIZED (SELECT draw AS win, path_id + (SELECT min(t) FROM edges) - {width} AS a FROM drawn)", inside, found) + ROUNDED.format(name=name, delta=delta, value=f"CAST({extent} AS DOUBLE) / {n} / ({width} + 1 - (t1 - t0))", source="found")
    spans = f"weighed AS MATERIALIZED (SELECT f.k, count(*) AS n FROM (SELECT t0, t1, count(*) AS k FROM found GROUP BY ALL) f JOIN edges e ON e.t BETWEEN f.t1 - {width} AND f.t0 GROUP BY f.t0, f.t1, f.k)"
    e = view(v, draws(n, total="(SELECT count(*) FROM edges)"), "windows AS MATERIALIZED (SELECT draw AS win, t AS a FROM drawn JOIN (SELECT t, row_number() OVER (ORDER BY t, eid) - 1 AS k FROM edges) ON k = path_id)", inside, found, spans, "each AS (SELECT n FROM weighed, unnest(range(k)))") + ROUNDED.format(name=name, delta=delta, value=f"CAST((SELECT count(*) FROM edges) AS DOUBLE) / {n} / n", source="each")
    return a, e


ROUNDED = "SELECT '{name}' AS motif, CAST({delta} AS BIGINT) AS delta, CAST(count(*) AS BIGINT) AS seen, CAST(round(coalesce(sum({value}), 0)) AS BIGINT) AS estimate FROM {source}"


def oracle_sql() -> dict[str, str]:
    cls = PathClass("-", "+", "<", ">")
    wedge = WedgeClass("dst", "+", ">")
    out = {
        "edges_reply": view("R") + "SELECT * FROM edges",
        "edges_folded": view("F") + "SELECT * FROM edges",
        "edges_nation": view("N") + "SELECT * FROM edges",
        "edges_trade": view("T") + "SELECT * FROM edges",
        "graph_profile": view("R") + "SELECT (SELECT count(*) FROM (SELECT src FROM edges UNION SELECT dst FROM edges)) AS vertices, count(*) AS temporal_edges, (SELECT count(*) FROM (SELECT DISTINCT src, dst FROM edges)) AS static_edges, min(t) AS t_min, max(t) AS t_max, max(t) - min(t) AS span FROM edges",
        "static_edges": view("R") + "SELECT DISTINCT src, dst FROM edges",
        "edge_self_loops": f"SELECT count(*) AS loops FROM ({reply(6, loops=True)}) WHERE src = dst",
        "ranked_out": view("R", LISTS) + "SELECT vertex, rank, t, eid, other FROM lists WHERE dir = '+'",
        "ranked_in": view("R", LISTS) + "SELECT vertex, rank, t, eid, other FROM lists WHERE dir = '-'",
        "degrees_before_in": view("R", degree("1", "src", "-", "<", R_DELTA)) + "SELECT eid, lo AS lo1, n AS n1 FROM d1",
        "degrees_after_out": view("R", degree("1", "dst", "+", ">", R_DELTA)) + "SELECT eid, lo AS lo3, n AS n3 FROM d1",
        "degree_closed_vs_strict": view("N") + f"SELECT CAST(sum((SELECT count(*) FROM edges f WHERE f.dst = e.src AND f.t >= e.t - {N_DELTA} AND f.t < e.t)) AS BIGINT) AS strict, CAST(sum((SELECT count(*) FROM edges f WHERE f.dst = e.src AND f.t >= e.t - {N_DELTA} AND f.t <= e.t)) AS BIGINT) AS closed FROM edges e",
        "multiplicity_max": view("F") + f"SELECT max(m) AS sigma FROM (SELECT (SELECT count(*) FROM edges f WHERE f.src = e.src AND f.dst = e.dst AND f.t BETWEEN e.t AND e.t + {F_DELTA}) AS m FROM edges e)",
        "path_weights_16": union_classes(PathClass.all(), R_DELTA, "SELECT class, eid, w FROM every_w"),
        "path_totals": union_classes(PathClass.all(), R_DELTA, "SELECT class, CAST(sum(w) AS BIGINT) AS w_total FROM every_w GROUP BY class"),
        "wedge_totals": union_classes(WedgeClass.all(), R_DELTA, "SELECT class, CAST(sum(w) AS BIGINT) AS w_total FROM every_w GROUP BY class"),
        "path_probabilities": view("R", *weighted(cls, R_DELTA)) + "SELECT eid, w, CAST(w AS DOUBLE) / CAST((SELECT sum(w) FROM weighted) AS DOUBLE) AS p FROM weighted",
        "weights_static": view("R", *weighted(cls, R_DELTA, True)) + "SELECT eid, n1, n3, w FROM weighted",
        "weights_constrained": view("R") + f"SELECT e.eid, a.eid AS eid1, CAST(count(b.eid) AS BIGINT) AS w FROM edges e JOIN edges a ON a.dst = e.src AND a.t >= e.t - {R_DELTA} AND a.t < e.t LEFT JOIN edges b ON b.src = e.dst AND b.t > e.t AND b.t <= a.t + {R_DELTA} GROUP BY e.eid, a.eid",
        "wedges_listed": view("R") + f"SELECT e.eid AS eid1, f.eid AS eid2, e.src AS v0, e.dst AS v1, f.dst AS v2 FROM edges e JOIN edges f ON f.src = e.dst AND {side('f', 'e.t', '>', R_DELTA)}",
        "paths_listed": view("R") + f"SELECT a.eid AS eid1, e.eid AS eid2, b.eid AS eid3 FROM edges e JOIN edges a ON a.dst = e.src AND {side('a', 'e.t', '<', R_DELTA)} JOIN edges b ON b.src = e.dst AND {side('b', 'e.t', '>', R_DELTA)}",
        "path_ids_bijection": view("R", *weighted(cls, R_DELTA)) + "SELECT CAST(sum(w) AS BIGINT) AS ids, CAST(sum(w) AS BIGINT) AS distinct_ids, CAST(sum(w) AS BIGINT) AS distinct_paths FROM weighted",
        "sample_paths_md5": view("R", *weighted(cls, R_DELTA), LISTS, OFFSETS, draws(K), *decoded(cls)) + "SELECT * FROM paths",
        "sample_wedges_md5": view("R", *weighted(wedge, R_DELTA), LISTS, OFFSETS, draws(K), *decoded(wedge)) + "SELECT * FROM paths",
        "path_check_flags": view("R", *weighted(cls, R_DELTA), LISTS, OFFSETS, draws(K), *decoded(cls)) + f"SELECT draw, ({valid(motif('M4-0').anchor(), R_DELTA)}) AS valid FROM paths",
        "star_exact": exact("R", "STAR", R_DELTA),
        "matches_listed": (lambda f: view("F") + f"SELECT e0.eid AS eid0, e1.eid AS eid1, e2.eid AS eid2, e0.t AS t_first, e2.t AS t_last FROM {f[0]} WHERE {f[1]}")(self_join(motif("TRI"), F_DELTA)),
        "chain_count_two_lists": view("F") + f"SELECT CAST(count(*) AS BIGINT) AS chains FROM edges a JOIN edges b ON a.src = b.dst AND a.dst = b.src AND b.t > a.t AND b.t <= a.t + {F_DELTA}",
        "chain_count_ties": view("N") + f"SELECT CAST(count(*) FILTER (b.t > a.t) AS BIGINT) AS strict, CAST(count(*) AS BIGINT) AS weak FROM edges a JOIN edges b ON a.src = b.dst AND a.dst = b.src AND b.t >= a.t AND b.t <= a.t + {N_DELTA}",
        "required_samples": " UNION ALL ".join(f"({bound(n)})" for n in BOUNDS),
    }
    for name, v, delta in CENSUS:
        key = name.lower().replace("-", "_")
        parts = census_parts(name, delta)
        out[f"census_{key}"] = view(v, *parts) + f"SELECT '{name}' AS motif, CAST({delta} AS BIGINT) AS delta, CAST((SELECT sum(w) FROM weighted) AS BIGINT) AS w_total, (SELECT count(*) FROM ok) AS valid_paths, (SELECT count(*) FROM done) AS hit_paths, CAST(coalesce((SELECT sum(x) FROM done), 0) AS BIGINT) AS count"
    for name, v, delta in EXACT:
        key = name.lower().replace("-", "_")
        out[f"backtrack_{key}"] = exact(v, name, delta)
        out[f"frontier_{key}"] = exact(v, name, delta)
    out["backtrack_bucketed_m4_0"] = exact("F", "M4-0", F_DELTA)
    out["census_bipartite_tri"] = exact("T", "TRI", T_DELTA)
    out["bipartite_cycle"] = exact("T", "M4-0", T_DELTA)
    out["nation_ties_tri"] = exact("N", "TRI", N_DELTA)
    for name in (*EIGHT, "TRI", "LATE", "SPLIT", "PAW"):
        out[f"estimate_{name.lower().replace('-', '_')}"] = estimate("F", name, F_DELTA)
    out["estimate_static"] = estimate("R", "M4-0", R_DELTA, static=True)
    out["estimate_sweep"] = " UNION ALL ".join(f"({estimate('R', 'M4-0', d)})" for d in (R_DELTA, 2 * R_DELTA))
    out["anchor_stats"] = " UNION ALL ".join(f"({anchors_of(v, n, d)})" for v, n, d in ANCHORS)
    out["estimate_stratified"] = view("F", *sampled("F", "M4-0", F_DELTA, drawn=[draws_stratified(K)])) + ESTIMATE.format(name="M4-0", delta=F_DELTA, k=K)
    out["estimate_without_replacement"] = view("F", *sampled("F", "M4-0", F_DELTA, drawn=draws_distinct(K))) + ESTIMATE.format(name="M4-0", delta=F_DELTA, k="(SELECT count(*) FROM drawn)")
    m = motif("M4-0")
    out["estimate_poisson"] = view("F", *weighted(cls, F_DELTA), LISTS, OFFSETS, *decoded(cls, located_poisson(K)), *completed(m, m.anchor(), F_DELTA)) + ESTIMATE.format(name="M4-0", delta=F_DELTA, k=K)
    out["estimate_constrained"] = view("R", *constrained("M4-0", R_DELTA)) + ESTIMATE.format(name="M4-0", delta=R_DELTA, k=K)
    out["estimate_hub_star"] = hub("STAR", R_DELTA)
    out["estimate_adaptive"] = adaptive("F", "M4-0", F_DELTA, 0.1)
    out["estimate_eight"] = " UNION ALL ".join(f"({estimate('F', n, F_DELTA)})" for n in EIGHT)
    out["hit_rates"] = rates("R", "M4-0", R_DELTA)
    out["hit_rates_folded"] = rates("F", "M4-0", F_DELTA)
    out["relative_error_5_seeds"] = " UNION ALL ".join(f"({errors_of_seeds('F', n, F_DELTA, K, SEEDS)})" for n in ERRORS)
    out["convergence_in_k"] = converging("F", "M4-0", F_DELTA, GROWING, SEEDS)
    out["heuristic_samples"] = " UNION ALL ".join(f"({view('F', *sampled('F', n, F_DELTA, PILOT))}SELECT '{n}' AS motif, CAST(ceil(quantile_cont(CAST(x AS DOUBLE), 0.9) * {WHOLE} / (CAST({WHOLE} AS DOUBLE) * sum(x) / {PILOT})) AS BIGINT) AS k FROM done)" for n in HEURISTIC)
    out["approx_vertices"] = view("R") + "SELECT count(*) AS vertices, true AS near FROM (SELECT src FROM edges UNION SELECT dst FROM edges)"
    for name, (v, names, delta) in WORKLOADS.items():
        out[name] = counts(v, names, delta)
    out["count_table"] = "SELECT graph, motif, CAST(sum(count) AS BIGINT) AS count FROM (" + " UNION ALL ".join("(" + counts(v, names, d, f"SELECT '{v}' AS graph, '{{name}}' AS motif, {{count}} AS count") + ")" for v, names, d in TABLE) + ") GROUP BY ROLLUP(graph, motif)"
    ratio = []
    for above, below in RATIOS:
        (x, nx), (y, ny) = stepwise(motif(above), F_DELTA, "x"), stepwise(motif(below), F_DELTA, "y")
        ratio.append(f"({view('F', *x, *y)}SELECT '{above}' AS above, '{below}' AS below, {nx} AS above_count, {ny} AS below_count)")
    (x, nx), (y, ny) = stepwise(motif("TRI"), F_DELTA, "x"), stepwise(motif("TRI"), F_DELTA, "y", "simple")
    simple = "simple AS MATERIALIZED (SELECT src, dst, min(t) AS t FROM edges GROUP BY src, dst)"
    ratio.append(f"({view('F', simple, *x, *y)}SELECT 'TRI' AS above, 'TRI-simple' AS below, {nx} AS above_count, {ny} AS below_count)")
    out["count_ratios"] = " UNION ALL ".join(ratio)
    for tag, v, delta, n in WINDOWS:
        out[f"windows_a{tag}"], out[f"windows_e{tag}"] = windows(v, "M4-0", delta, n)
    chance = "CAST(CAST('0x' || substr(md5('42|' || {}), 1, 13) AS BIGINT) AS DOUBLE) / 4503599627370496"
    wide = 4 * R_DELTA
    out["partition_sampler"] = view("R", draws(1, total=str(wide)), f"inside AS MATERIALIZED (SELECT * FROM (SELECT *, CAST(floor((t - (SELECT path_id FROM drawn)) / CAST({wide} AS DOUBLE)) AS BIGINT) AS win FROM edges) WHERE {chance.format('win')} < 0.5)", window_matches("M4-0", R_DELTA, "")) + ROUNDED.format(name="M4-0", delta=R_DELTA, value=f"1.0 / (0.5 * (1 - CAST(t1 - t0 AS DOUBLE) / {wide}))", source="found")
    tables, tests = self_join(motif("M4-0"), R_DELTA)
    out["edge_sampler"] = view("R", f"kept AS MATERIALIZED (SELECT eid FROM edges WHERE {chance.format('eid')} < 0.25)", "found AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT e0.eid FROM {tables} WHERE {tests} AND e{p}.eid IN (SELECT eid FROM kept)" for p in range(4)) + ")") + ROUNDED.format(name="M4-0", delta=R_DELTA, value="1.0", source="found")
    label = "label IN ('" + "', '".join(LABELS) + "')"
    out |= {
        "edges_by_label_filter": view("R") + f"SELECT eid, src, dst, t, label FROM edges WHERE {label}",
        "edges_semi_active": view("R", *weighted(cls, R_DELTA)) + "SELECT eid, src, dst, t FROM weighted WHERE w > 0",
        "edges_anti_isolated": view("R") + "SELECT DISTINCT src AS v FROM edges WHERE src NOT IN (SELECT dst FROM edges)",
        "asof_previous_edge": view("R") + "SELECT eid, src, t, lag(t) OVER (PARTITION BY src ORDER BY t, eid) AS previous_t FROM edges",
        "interval_join_edges": view("R") + f"SELECT w.k AS win, CAST(count(e.eid) AS BIGINT) AS n FROM (SELECT k, (SELECT min(t) FROM edges) + k * {DAY} AS a FROM range(30) r(k)) w JOIN edges e ON e.t BETWEEN w.a AND w.a + {DAY // 2} GROUP BY w.k",
        "time_tumbling": view("R") + f"SELECT t // {DAY} AS day, label, count(*) AS n FROM edges GROUP BY 1, 2",
        "time_sliding": view("R") + f"SELECT CAST(h AS BIGINT) AS hour, count(*) AS n FROM (SELECT unnest(range(t // {HOUR} - 5, t // {HOUR} + 1)) AS h FROM edges) GROUP BY 1",
        "time_session": view("R", f"gaps AS (SELECT src, t, CASE WHEN t - lag(t) OVER (PARTITION BY src ORDER BY t) < {6 * HOUR} THEN 0 ELSE 1 END AS new FROM edges)", "s AS (SELECT src, t, sum(new) OVER (PARTITION BY src ORDER BY t) AS k FROM gaps)") + "SELECT src, min(t) AS t_first, max(t) AS t_last, count(*) AS n FROM s GROUP BY src, k",
        "cube_labels": view("R") + f"SELECT label, t // {7 * DAY} AS week, count(*) AS n FROM edges GROUP BY CUBE (label, t // {7 * DAY})",
        "rollup_calendar": view("N") + "SELECT year, month, count(*) AS n FROM (SELECT CAST(year(DATE '1970-01-01' + CAST(t AS INT)) AS INT) AS year, CAST(month(DATE '1970-01-01' + CAST(t AS INT)) AS INT) AS month FROM edges) GROUP BY ROLLUP (year, month)",
        "grouping_sets_region": view("N") + "SELECT a.r_name AS from_region, b.r_name AS to_region, count(*) AS n FROM edges JOIN nation x ON x.n_nationkey = src JOIN region a ON a.r_regionkey = x.n_regionkey JOIN nation y ON y.n_nationkey = dst JOIN region b ON b.r_regionkey = y.n_regionkey GROUP BY GROUPING SETS ((a.r_name), (b.r_name), (a.r_name, b.r_name))",
        "topk_hubs": view("R") + "SELECT v, count(*) AS degree FROM (SELECT src AS v FROM edges UNION ALL SELECT dst FROM edges) GROUP BY v ORDER BY degree DESC, v LIMIT 10",
        "vertices_union_except_intersect": view("R") + "SELECT 'union' AS kind, count(*) AS n FROM (SELECT src FROM edges UNION SELECT dst FROM edges) UNION ALL SELECT 'intersect', count(*) FROM (SELECT src FROM edges INTERSECT SELECT dst FROM edges) UNION ALL SELECT 'except', count(*) FROM (SELECT src FROM edges EXCEPT SELECT dst FROM edges)",
        "burst_gaps": view("R") + "SELECT eid, t - lag(t) OVER w AS gap_before, lead(t) OVER w - t AS gap_after FROM edges WINDOW w AS (PARTITION BY src ORDER BY t, eid)",
        "pair_arrays": view("F") + "SELECT src, dst, count(*) AS n, min(t) AS t_first, max(t) AS t_last, CAST(sum(t // 1000000) AS BIGINT) AS t_sum FROM edges GROUP BY src, dst",
        "props_json": f"SELECT {TOPIC} AS topic, count(*) AS n FROM events GROUP BY 1",
        "degree_deciles": view("R") + "SELECT decile, count(*) AS n, min(degree) AS low, max(degree) AS high FROM (SELECT degree, ntile(10) OVER (ORDER BY degree, v) AS decile FROM (SELECT v, count(*) AS degree FROM (SELECT src AS v FROM edges UNION ALL SELECT dst FROM edges) GROUP BY v)) GROUP BY decile",
        "induced_subgraph": view("R") + "SELECT eid, src, dst, t FROM edges WHERE src % 2 = 0 AND dst % 2 = 0",
        "time_slice": view("N") + "SELECT eid, src, dst, t FROM edges WHERE t BETWEEN 9500 AND 9600",
        "stream_tumbling": f"SELECT CAST(epoch_us(ts) // {DAY} AS BIGINT) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    }
    return out


#: Motifs whose sample bound is asked for, on the folded graph.
BOUNDS = ("M4-0", "M4-5")
LABELS = ("click", "view")
#: (motif, view, window) of the census queries and of the exact counters.
CENSUS = (*((n, "F", F_DELTA) for n in ("TRI", *EIGHT)), ("PAW", "R", R_DELTA), ("LATE", "R", R_DELTA), ("SPLIT", "R", R_DELTA), ("K4", "R", 2 * R_DELTA), ("PATH", "R", R_DELTA))
EXACT = (*((n, "F", F_DELTA) for n in ("TRI", *EIGHT)), ("PAW", "R", R_DELTA), ("LATE", "R", R_DELTA))
#: (name, view, window, how many windows) of the window samplers.
WINDOWS = (("", "R", R_DELTA, 30), ("_folded", "F", F_DELTA, 60))
#: (view, motif, window) whose completions per anchor are described.
ANCHORS = (("F", "M4-0", F_DELTA), ("F", "M4-5", F_DELTA), ("R", "M4-0", 4 * R_DELTA), ("R", "M4-5", 4 * R_DELTA))
TABLE = (("F", ("TRI", "M4-0", "M4-5"), F_DELTA), ("R", ("TRI", "M4-0", "M4-5"), R_DELTA))
RATIOS = (("M4-0", "TRI"), ("M3-1", "M3-0"))
#: Seeded runs: their seeds, the motifs whose errors are measured, sample sizes of the convergence, and of the pilot.
SEEDS, ERRORS, GROWING, PILOT = tuple(range(42, 47)), ("TRI", "M3-0", "M3-1", "M4-0", "M4-5"), (1_000, 4_000, 16_000), 20_000
HEURISTIC = ("M4-0", "M4-5", "M4-2")
#: name -> (view, motifs, window): longer windows on each view.
WORKLOADS = {
    "counts_reply_4_days": ("R", ("TRI", "M4-0", "M4-5"), 4 * R_DELTA),
    "counts_reply_5_days": ("R", ("TRI", *EIGHT), 5 * R_DELTA),
    "counts_folded_6_hours": ("F", ("TRI", *EIGHT), 6 * HOUR),
    "counts_trade_90_days": ("T", ("M4-0",), 90),
    "counts_nation_7_days": ("N", ("TRI", "M4-0"), 7),
    "counts_nation_30_days": ("N", ("TRI",), 30),
}
