"""DuckDB SQL of the registered queries; loops are written out sweep by sweep."""

from __future__ import annotations

import math

import numpy as np

from ..functions.kernels import KernelSpec, cosine, linear, polynomial, rbf, sigmoid
from ..functions.points import LINE4, LINE_KEY, USER, WIDE28

LOG2 = "ln({}) / ln(2)"
KEY = ", ".join(LINE_KEY)


def z(cols: list[str], inner: str, extra: str) -> str:
    """z-scores of ``cols`` of a subquery, other columns as ``extra``."""
    parts = ", ".join(f"CASE WHEN stddev_pop({c}) OVER () > 0 THEN ({c} - avg({c}) OVER ()) / stddev_pop({c}) OVER () ELSE 0.0 END AS {c}" for c in cols)
    return f"SELECT {extra}, {parts} FROM ({inner})"


def _list(cols: list[str]) -> str:
    return "[" + ", ".join(cols) + "]"


EMB = "SELECT row_number() OVER (ORDER BY vec_id) - 1 AS idx, vec_id AS key, CAST(embedding AS DOUBLE[]) AS x FROM embeddings"


def line4() -> str:
    inner = f"SELECT row_number() OVER (ORDER BY {KEY}) - 1 AS idx, l_orderkey AS key, {', '.join(LINE4)} FROM lineitem"
    return f"SELECT idx, key, {_list(LINE4)} AS x FROM ({z(LINE4, inner, 'idx, key')})"


def wide28() -> str:
    def cyc(value: str, period: int) -> list[str]:
        turn = f"{value} * {2 * math.pi / period!r}"
        return [f"sin({turn})", f"cos({turn})"]

    def hot(col: str, values: list[str]) -> list[str]:
        return [f"CASE WHEN {col} = '{v}' THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END" for v in values]

    features = [
        *LINE4, *cyc("month(l_shipdate)", 12), *cyc("(dayofweek(l_shipdate) + 1)", 7), "year(l_shipdate)::DOUBLE", *hot("l_returnflag", ["A", "N", "R"]), *hot("l_linestatus", ["F", "O"]), "o_totalprice",
        *hot("o_orderstatus", ["F", "O", "P"]), *hot("substr(o_orderpriority, 1, 1)", ["1", "2", "3", "4", "5"]), "p_size::DOUBLE", "p_retailprice", "s_acctbal", "c_acctbal", "date_diff('day', o_orderdate::DATE, l_shipdate::DATE)::DOUBLE",
    ]
    named = ", ".join(f"{f} AS {c}" for f, c in zip(features, WIDE28))
    inner = f"""SELECT row_number() OVER (ORDER BY {KEY}) - 1 AS idx, l_orderkey AS key, {named} FROM lineitem
      JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey"""
    return f"SELECT idx, key, {_list(WIDE28)} AS x FROM ({z(WIDE28, inner, 'idx, key')})"


def docbag(m: int) -> str:
    return f"""
  SELECT row_number() OVER (ORDER BY d.doc_id) - 1 AS idx, d.doc_id AS key, list_transform(range({m}), lambda i: coalesce(map_extract(h.m, i)[1] / h.norm, 0.0)) AS x,
    CAST(list_position(['de', 'en', 'es', 'fr'], d.lang) - 1 AS INTEGER) AS truth
  FROM documents d LEFT JOIN (
    SELECT doc_id, map(list(b), list(c)) AS m, sqrt(sum(c * c)) AS norm FROM (
      SELECT doc_id, ('0x' || substr(md5(t), 1, 8))::BIGINT % {m} AS b, count(*)::DOUBLE AS c
      FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\\p{{L}}+')) AS t FROM documents) GROUP BY 1, 2) GROUP BY doc_id) h ON h.doc_id = d.doc_id"""


def eventday() -> str:
    hour = f"(hour(ts) + minute(ts) / 60.0 + second(ts) / 3600.0) * {2 * math.pi / 24!r}"
    inner = f"SELECT row_number() OVER (ORDER BY event_id) - 1 AS idx, event_id AS key, sin({hour}) AS h0, cos({hour}) AS h1, ln(1 + value) AS v, CAST(json_extract(props, '$.k') AS DOUBLE) AS k FROM events"
    return f"SELECT idx, key, [h0, h1, v, k] AS x FROM ({z(['v', 'k'], inner, 'idx, key, h0, h1')})"


def userfeat() -> str:
    counts = ", ".join(f"sum(CASE WHEN event_type = '{c[2:]}' THEN 1.0 ELSE 0.0 END)::DOUBLE AS {c}" for c in USER[:5])
    inner = f"SELECT row_number() OVER (ORDER BY user_id) - 1 AS idx, user_id AS key, {counts}, sum(value) AS total, avg(value) AS mean, (epoch((SELECT max(ts) FROM events)) - epoch(max(ts))) / 3600.0 AS recency FROM events GROUP BY user_id"
    return f"SELECT idx, key, {_list(USER)} AS x FROM ({z(USER, inner, 'idx, key')})"


PART2 = f"SELECT idx, key, [s, r] AS x FROM ({z(['s', 'r'], 'SELECT row_number() OVER (ORDER BY p_partkey) - 1 AS idx, p_partkey AS key, p_size::DOUBLE AS s, p_retailprice AS r FROM part', 'idx, key')})"
_LOBE = "SELECT c_custkey AS key, c_acctbal AS bal, CAST(c_acctbal > 4500 AS INTEGER) AS y, CASE WHEN (c_custkey // 2) % 2 = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS s, 2 + fmod(fmod(c_acctbal, 100.0::DOUBLE) + 100.0::DOUBLE, 100.0::DOUBLE) / 100 AS a, fmod(fmod(7 * c_acctbal, 100.0::DOUBLE) + 100.0::DOUBLE, 100.0::DOUBLE) / 100 - 0.5::DOUBLE AS b FROM customer"
LOBES = f"SELECT row_number() OVER (ORDER BY key) - 1 AS idx, key, CASE WHEN y = 0 THEN [s * a, b] ELSE [b, s * a] END AS x, y AS truth FROM ({_LOBE})"
_RING = f"SELECT c_custkey AS key, CAST(c_acctbal > 4500 AS INTEGER) AS y, {2 * math.pi!r} * (0.6180339887::DOUBLE * c_custkey - floor(0.6180339887::DOUBLE * c_custkey)) AS t, fmod(fmod(c_acctbal, 100.0::DOUBLE) + 100.0::DOUBLE, 100.0::DOUBLE) / 100 AS u FROM customer"
RINGS = f"SELECT row_number() OVER (ORDER BY key) - 1 AS idx, key, [(CASE WHEN y = 1 THEN 1.0::DOUBLE ELSE 3.0::DOUBLE END + 0.2::DOUBLE * u) * cos(t), (CASE WHEN y = 1 THEN 1.0::DOUBLE ELSE 3.0::DOUBLE END + 0.2::DOUBLE * u) * sin(t)] AS x, y AS truth FROM ({_RING})"
MINI = "SELECT * FROM (VALUES (0, 0, [1.0::DOUBLE], 0), (1, 1, [2.0::DOUBLE], 1), (2, 2, [-1.0::DOUBLE], 0), (3, 3, [-2.0::DOUBLE], 1)) AS t(idx, key, x, truth)"


def gram(points: str, kernel: KernelSpec) -> str:
    return f"""p AS MATERIALIZED ({points}),
q AS MATERIALIZED (SELECT idx, x, list_dot_product(x, x) AS nn FROM p),
ke AS MATERIALIZED (SELECT i, j, {kernel.sql("b")} AS v FROM (SELECT s.idx AS i, t.idx AS j, s.nn AS ni, t.nn AS nj, list_dot_product(s.x, t.x) AS b FROM q s, q t))"""


def loop(points: str, kernel: KernelSpec, k: int, sweeps: int, empty: str = "skip") -> str:
    """CTEs p, ke and, for t = 1..sweeps, e{t}, c{t}, d{t} and labels l{t} from l{t-1}; l0 is the round-robin start."""
    parts = [gram(points, kernel), f"l0 AS MATERIALIZED (SELECT idx, idx % {k} AS cl FROM p)"]
    for t in range(1, sweeps + 1):
        old = f"l{t - 1}"
        parts += [
            f"e{t} AS MATERIALIZED (SELECT ke.i, l.cl, avg(ke.v) AS e FROM ke JOIN {old} l ON ke.j = l.idx GROUP BY ke.i, l.cl)",
            f"c{t} AS MATERIALIZED (SELECT l.cl, avg(e.e) AS c FROM e{t} e JOIN {old} l ON e.i = l.idx AND e.cl = l.cl GROUP BY l.cl)",
        ]
        rows = f"SELECT e.i, e.cl, c.c - 2 * e.e AS dist FROM e{t} e JOIN c{t} c ON e.cl = c.cl"
        if empty == "origin":
            rows += f" UNION ALL SELECT p.idx, r.range, 0.0 FROM p, range({k}) r WHERE r.range NOT IN (SELECT cl FROM {old})"
        parts += [f"d{t} AS MATERIALIZED ({rows})", f"l{t} AS MATERIALIZED (SELECT i AS idx, min({{'dist': dist, 'cl': cl}}).cl AS cl FROM d{t} GROUP BY i)"]
    return "WITH " + ",\n".join(parts)


def labels(points: str, kernel: KernelSpec, k: int, sweeps: int, empty: str = "skip") -> str:
    return f"{loop(points, kernel, k, sweeps, empty)}\nSELECT idx, CAST(cl AS INTEGER) AS cl FROM l{sweeps}"


def settled(points: str, kernel: KernelSpec, k: int) -> str:
    """As ``labels``, with as many sweeps as it takes until no label changes."""
    return f"""WITH RECURSIVE {gram(points, kernel)},
l(t, idx, cl) AS (
  SELECT 0, idx, idx % {k} FROM p
  UNION ALL
  SELECT * FROM (
    WITH e AS MATERIALIZED (SELECT ke.i, l.cl, avg(ke.v) AS e FROM ke JOIN l ON ke.j = l.idx GROUP BY ke.i, l.cl),
    c AS (SELECT l.cl, avg(e.e) AS c FROM e JOIN l ON e.i = l.idx AND e.cl = l.cl GROUP BY l.cl),
    n AS MATERIALIZED (SELECT e.i AS idx, min({{'dist': c.c - 2 * e.e, 'cl': e.cl}}).cl AS cl FROM e JOIN c ON e.cl = c.cl GROUP BY e.i)
    SELECT (SELECT max(t) FROM l) + 1, idx, cl FROM n WHERE EXISTS (SELECT 1 FROM n a JOIN l ON a.idx = l.idx WHERE a.cl <> l.cl)))
SELECT idx, CAST(cl AS INTEGER) AS cl FROM l WHERE t = (SELECT max(t) FROM l)"""


def lift_loop(points: str, dim: int, k: int, sweeps: int, empty: str = "skip") -> str:
    """As ``loop`` for the kernel (<x, y> + 1) ** 2 in its explicit feature space: means in place of a matrix, so whole tables are cheap.

    Reseeding: a cluster keeps its nearest member, its others are open by distance;
    the empty clusters, by id, take the farthest open points of all.
    """
    terms = [f"x[{i}] * x[{i}]" for i in range(1, dim + 1)] + [f"sqrt(2.0::DOUBLE) * x[{i}] * x[{j}]" for i in range(1, dim + 1) for j in range(i + 1, dim + 1)] + [f"sqrt(2.0::DOUBLE) * x[{i}]" for i in range(1, dim + 1)] + ["1.0::DOUBLE"]
    parts = [f"p AS MATERIALIZED ({points})", f"f AS MATERIALIZED (SELECT idx, [{', '.join(terms)}] AS f FROM p)", f"l0 AS MATERIALIZED (SELECT idx, idx % {k} AS cl FROM p)"]
    mean = "[" + ", ".join(f"avg(f.f[{i}])" for i in range(1, len(terms) + 1)) + "]"
    for t in range(1, sweeps + 1):
        old = f"l{t - 1}"
        parts.append(f"m{t} AS MATERIALIZED (SELECT cl, c, list_dot_product(c, c) AS cc FROM (SELECT l.cl, {mean} AS c FROM f JOIN {old} l USING (idx) GROUP BY l.cl))")
        rows = f"SELECT f.idx, m.cl, m.cc - 2 * list_dot_product(f.f, m.c) AS dist FROM f, m{t} m"
        if empty == "origin":
            rows += f" UNION ALL SELECT p.idx, r.range, 0.0 FROM p, range({k}) r WHERE r.range NOT IN (SELECT cl FROM {old})"
        least = f"SELECT idx, min({{'dist': dist, 'cl': cl}}) AS b FROM ({rows}) GROUP BY idx"
        if empty != "reseed":
            parts.append(f"l{t} AS MATERIALIZED (SELECT idx, b.cl AS cl FROM ({least}))")
            continue
        parts += [
            f"n{t} AS MATERIALIZED (SELECT a.idx, a.b.cl AS cl, a.b.dist + list_dot_product(f.f, f.f) AS sq FROM ({least}) a JOIN f USING (idx))",
            f"o{t} AS MATERIALIZED (SELECT idx, row_number() OVER (ORDER BY sq DESC, idx) AS place FROM (SELECT *, row_number() OVER (PARTITION BY cl ORDER BY sq DESC, idx) AS r, count(*) OVER (PARTITION BY cl) AS c FROM n{t}) WHERE r < c)",
            f"v{t} AS MATERIALIZED (SELECT r.range AS cl, row_number() OVER (ORDER BY r.range) AS place FROM range({k}) r WHERE r.range NOT IN (SELECT cl FROM n{t}))",
            f"l{t} AS MATERIALIZED (SELECT n.idx, coalesce(g.cl, n.cl) AS cl FROM n{t} n LEFT JOIN (SELECT o.idx, v.cl FROM o{t} o JOIN v{t} v USING (place)) g USING (idx))",
        ]
    return "WITH " + ",\n".join(parts)


def lift_labels(points: str, dim: int, k: int, sweeps: int, empty: str = "skip") -> str:
    return f"{lift_loop(points, dim, k, sweeps, empty)}\nSELECT idx, CAST(cl AS INTEGER) AS cl FROM l{sweeps}"


def r6(x: str) -> str:
    return f"round({x}, 6) + 0.0"


POLY = polynomial()
ONE = loop(EMB, POLY, 10, 1)
RUNS = [
    ("a", 16, "mixed", 1, "kernel", 4.0), ("a", 16, "mixed", 1, "sweep", 4.0), ("a", 16, "mixed", 4, "kernel", 1.5), ("a", 16, "mixed", 4, "sweep", 1.0), ("a", 16, "panel", 1, "kernel", 5.0),
    ("a", 16, "panel", 4, "kernel", 4.0), ("b", 32, "mixed", 1, "kernel", 8.0), ("b", 32, "mixed", 4, "kernel", 2.5), ("b", 32, "panel", 1, "kernel", 9.0), ("b", 32, "panel", 4, "kernel", 7.5),
]
RUNS_SQL = "runs AS (SELECT * FROM (VALUES " + ", ".join(f"('{a}', {b}::BIGINT, '{c}', {d}::BIGINT, '{e}', {f}::DOUBLE)" for a, b, c, d, e, f in RUNS) + ") AS t(dataset, k, algo, g, stage, seconds))"
GRID = [(n, d, k, p) for p in (4, 64, 256) for n, d in ((192_000, 784), (1_536_000, 784), (192_000, 10_000)) for k in (16, 64)]
GRID_SQL = "par AS (SELECT n, d, k, p, n::DOUBLE AS nn, d::DOUBLE AS dd, k::DOUBLE AS kk, p::DOUBLE AS pp, sqrt(p::DOUBLE) AS root FROM (VALUES " + ", ".join(f"({n}::BIGINT, {d}::BIGINT, {k}::BIGINT, {p}::BIGINT)" for n, d, k, p in GRID) + ") AS t(n, d, k, p))"


EVENT_SETS_SQL = "par AS (SELECT n, d, k, p, n::DOUBLE AS nn, d::DOUBLE AS dd, k::DOUBLE AS kk, p::DOUBLE AS pp, sqrt(p::DOUBLE) AS root FROM (SELECT count(*) AS n, count(DISTINCT user_id) AS d FROM events GROUP BY event_type), (VALUES (16::BIGINT), (64::BIGINT)) AS ks(k), (VALUES (4::BIGINT), (64::BIGINT), (256::BIGINT)) AS ps(p))"
EVENT_COUNTS = "SELECT DISTINCT count(*) AS c FROM events GROUP BY user_id"


def _costs() -> str:
    rows = {
        "1d": ("pp", "pp * nn * dd", "pp", "nn"), "h1d": ("pp + root", "nn * nn / pp + nn * dd / root", "pp", "nn"),
        "2d": ("root", "nn * dd / root", "root + 1.0", "nn * (kk + 1) / root + nn"), "1.5d": ("root", "nn * dd / root", "root + 1.0", "nn * (kk + 1) / root"),
    }
    out = []
    for algo, (km, kw, dm, dw) in rows.items():
        each, total = (f"{kw} / pp", kw) if algo == "1d" else (kw, f"({kw}) * pp")
        out.append(f"SELECT '{algo}' AS algo, n, d, k, p, {km} AS kernel_messages, {kw} AS kernel_words, {dm} AS sweep_messages, {dw} AS sweep_words, {each} AS kernel_per_worker, {total} AS kernel_aggregate FROM par")
    return f"WITH {EVENT_SETS_SQL} SELECT algo, n, d, k, p, " + ", ".join(f"round({c}, 3) AS {c}" for c in ("kernel_messages", "kernel_words", "sweep_messages", "sweep_words", "kernel_per_worker", "kernel_aggregate")) + " FROM (" + " UNION ALL ".join(out) + ")"


def _memory(last: str) -> str:
    rows = {"1d": "nn * nn / pp + nn * dd + nn + kk * nn / pp", "h1d": "2 * nn * nn / pp + 2 * nn * dd / root + nn", "2d": "nn * nn / pp + nn * kk / root + 2 * nn * dd / root", "1.5d": "nn * nn / pp + 2 * nn * dd / root + nn * kk / root + nn / root"}
    return f"WITH {EVENT_SETS_SQL} SELECT algo, n, d, k, p, {last} FROM (" + " UNION ALL ".join(f"SELECT '{a}' AS algo, n, d, k, p, ({w}) * 4 AS memory_bytes FROM par" for a, w in rows.items()) + ")"


def _against(name: str) -> str:
    return f"WITH {RUNS_SQL}, t AS (SELECT dataset, k, algo, g, sum(seconds) AS seconds FROM runs GROUP BY ALL) SELECT *, first_value(seconds) OVER (PARTITION BY dataset, k, algo ORDER BY g) / seconds AS {name} FROM t"


EXACT = ("panel_1d", "regrid_h1d", "tile_2d", "mixed_15d")


def _moves(engine: str, d: str, k: str, g: int, sweeps: int) -> str:
    """List of (stage, item, words): what the shuffles of an engine must carry for n points, were nothing else moved."""
    p = g * g
    step = f"CAST(ceil(n / {p}.0) AS BIGINT)"
    wide = [f"greatest(least(n, {(j + 1) * g} * {step}) - least(n, {j * g} * {step}), 0)" for j in range(g)]
    pairs = " + ".join(f"CASE WHEN {w} > 0 THEN least({g}, {k}) * (CAST(ceil({w} / 2.0) AS BIGINT) + {w} + {k}) ELSE 0 END" for w in wide)
    rows = [("kernel", "points", f"{p if engine == 'panel_1d' else 2 * g} * n * {d}")]
    rows += [("kernel", "regrid", "n * n")] if engine == "regrid_h1d" else []
    rows += [("sweep", "pieces", f"{sweeps * g} * n * {k}")] if engine in ("tile_2d", "mixed_15d") else []
    rows += [("sweep", "minimum_pairs", f"{sweeps} * ({pairs})")] if engine == "tile_2d" and g > 1 else []
    rows += [("sweep", "labels", f"{sweeps * p} * n"), ("sweep", "norms_sizes", f"{sweeps * 2 * p} * {k}")]
    return "[" + ", ".join(f"{{'stage': '{s}', 'item': '{i}', 'words': CAST({w} AS BIGINT)}}" for s, i, w in rows) + "]"


SETS = {"vision": ("embeddings", 64, 500), "physics": ("lineitem", 28, 500), "education": ("documents", 1024, 500)}


def scaling(name: str, weak: bool) -> str:
    """Words by stage of every engine, k and grid on a set: what ``experiments`` must measure."""
    table_name, d, cap = SETS[name]
    out = []
    for g in (1, 2, 4):
        n = f"least({cap}, c // 4) * {g}" if weak else f"least({4 * cap}, c)"
        for e in EXACT:
            out.append(f"SELECT '{name}' AS dataset, k, '{e}' AS algo, {g * g}::BIGINT AS g, n, stage, sum(words)::BIGINT AS words FROM (SELECT k, n, unnest({_moves(e, str(d), 'k', g, 2)}, recursive := true) FROM (SELECT {n} AS n, k FROM s, (VALUES (16::BIGINT), (32::BIGINT), (64::BIGINT)) AS ks(k))) GROUP BY ALL")
    return f"WITH s AS (SELECT count(*) AS c FROM {table_name}) " + " UNION ALL ".join(out)


def table_of(points: str, kernel: KernelSpec, k: int, sweeps: int) -> str:
    return f"{loop(points, kernel, k, sweeps)}, ct AS (SELECT l.cl, p.truth, count(*) AS cnt FROM l{sweeps} l JOIN p ON p.idx = l.idx GROUP BY ALL)"


_ARI = """SELECT round(CASE WHEN (a + b) / 2 = a * b / (n * (n - 1) / 2) THEN 1.0 ELSE (s - a * b / (n * (n - 1) / 2)) / ((a + b) / 2 - a * b / (n * (n - 1) / 2)) END, 6) + 0.0 AS ari FROM
 (SELECT sum(cnt * (cnt - 1) / 2) AS s, sum(cnt) AS n FROM ct), (SELECT sum(c * (c - 1) / 2) AS a FROM (SELECT sum(cnt) AS c FROM ct GROUP BY cl)), (SELECT sum(c * (c - 1) / 2) AS b FROM (SELECT sum(cnt) AS c FROM ct GROUP BY truth))"""
_NMI = """, n AS (SELECT sum(cnt) AS n FROM ct), ra AS (SELECT cl, sum(cnt) AS a FROM ct GROUP BY cl), rb AS (SELECT truth, sum(cnt) AS b FROM ct GROUP BY truth)
SELECT round(2 * i / (ha + hb), 6) + 0.0 AS nmi FROM (SELECT sum(cnt / n * ln(cnt * n / (a * b))) AS i FROM ct JOIN ra USING (cl) JOIN rb USING (truth), n),
 (SELECT -sum(a / n * ln(a / n)) AS ha FROM ra, n), (SELECT -sum(b / n * ln(b / n)) AS hb FROM rb, n)"""
_DOC = docbag(1024)
_SPARSE = f"""p AS MATERIALIZED (SELECT row_number() OVER (ORDER BY doc_id) - 1 AS idx, doc_id FROM documents),
b AS MATERIALIZED (SELECT doc_id, ('0x' || substr(md5(t), 1, 8))::BIGINT % 10000 AS b, count(*)::DOUBLE AS c FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\\p{{L}}+')) AS t FROM documents) GROUP BY 1, 2),
w AS MATERIALIZED (SELECT p.idx, b.b, b.c / sqrt(sum(b.c * b.c) OVER (PARTITION BY b.doc_id)) AS v FROM b JOIN p USING (doc_id)),
dots AS MATERIALIZED (SELECT x.idx AS i, y.idx AS j, sum(x.v * y.v) AS b FROM w x JOIN w y ON x.b = y.b GROUP BY 1, 2),
ke AS MATERIALIZED (SELECT x.idx AS i, y.idx AS j, pow(coalesce(d.b, 0.0) + 1, 2) AS v FROM p x CROSS JOIN p y LEFT JOIN dots d ON d.i = x.idx AND d.j = y.idx)"""
_WIDE_LOOP = loop("SELECT 1", POLY, 4, 7)
_WIDE_LOOP = "WITH " + _SPARSE + ",\n" + _WIDE_LOOP[_WIDE_LOOP.index("l0 AS") :]

EMB_LABELS = labels(EMB, POLY, 10, 17)
HOLD = "SELECT * FROM p WHERE idx % 5 = 0"
SAMPLED = f"SELECT {KEY} FROM lineitem ORDER BY md5(concat_ws('|', '7', l_orderkey, l_linenumber, l_partkey, l_suppkey, strftime(l_shipdate, '%Y-%m-%d %H:%M:%S'))), {KEY} LIMIT 1000"
_FINAL = f"{loop(EMB, POLY, 10, 17)}, final AS (SELECT l.idx, l.cl FROM l17 l), fe AS (SELECT ke.i, f.cl, avg(ke.v) AS e FROM ke JOIN final f ON ke.j = f.idx GROUP BY ALL), fc AS (SELECT f.cl, avg(fe.e) AS c FROM fe JOIN final f ON fe.i = f.idx AND fe.cl = f.cl GROUP BY f.cl)"

_STEP_LOGS = {"1d": ("pp", "pp * nn * dd", "pp", "nn"), "h1d": ("pp + root * lg", "nn * nn / pp + nn * dd / root * lg", "pp", "nn"), "2d": ("root * lg", "nn * dd / root * lg", "root + lg", "nn * (kk + 1) / root + nn * lg"), "1.5d": ("root * lg", "nn * dd / root * lg", "root + lg", "nn * (kk + 1) / root")}
_LOGS = f"WITH {EVENT_SETS_SQL}, lpar AS (SELECT *, log2(root) AS lg FROM par) "


def drawn_features(m: int, dim: int, seed: int) -> str:
    """SQL list of the features that ``sample_features`` keeps."""
    kept = np.sort(np.random.Generator(np.random.PCG64(seed)).choice(dim, size=m, replace=False))
    return _list([f"x[{int(i) + 1}]" for i in kept])


def drawn_projection(m: int, dim: int, seed: int) -> str:
    """SQL list of the products with the rows that ``project`` draws."""
    rows = np.random.Generator(np.random.PCG64(seed)).normal(0, 1 / math.sqrt(m), (m, dim))
    return _list([f"list_dot_product(x, {_list([f'{float(v)!r}::DOUBLE' for v in row])})" for row in rows])


def entries_of(vectors: str) -> str:
    return f"SELECT idx, CAST(g AS INTEGER) AS pos, {r6('y[g]')} AS v FROM (SELECT idx, y, unnest(range(1, len(y) + 1)) AS g FROM (SELECT idx, {vectors} AS y FROM ({EMB})))"


ORACLES: dict[str, str] = {
    # kernel stage
    **{f"gram_{name}": f"WITH {gram(EMB, spec)} SELECT i, j, {r6('v')} AS v FROM ke" for name, spec in (("linear", linear()), ("poly", POLY), ("rbf", rbf(0.5)), ("sigmoid", sigmoid(0.5, 0.1)), ("cosine", cosine()))},
    "gram_tiles_checksum": f"WITH {gram(EMB, POLY)}, b AS (SELECT CAST(least(i // (4 * s), 1) AS INTEGER) AS x0, i, j, v, s FROM ke, (SELECT CAST(ceil(count(*) / 4.0) AS BIGINT) AS s FROM p)) SELECT CAST(i // (2 * s) AS INTEGER) AS bi, CAST(j // (2 * s) AS INTEGER) AS bj, count(*) AS cells, {r6('sum(v)')} AS total FROM b GROUP BY ALL",
    "gram_symmetric_half": f"WITH {gram(EMB, POLY)} SELECT i, {r6('sum(v)')} AS row_sum FROM ke GROUP BY i",
    "kernel_diag": f"WITH {gram(EMB, POLY)} SELECT i, {r6('v')} AS v FROM ke WHERE i = j",
    "kernel_trace": f"WITH {gram(EMB, POLY)} SELECT {r6('sum(v)')} AS trace FROM ke WHERE i = j",
    # membership
    "init_round_robin": f"WITH p AS ({EMB}) SELECT idx, CAST(idx % 10 AS INTEGER) AS cl FROM p",
    "sizes_initial": f"WITH p AS ({EMB}) SELECT CAST(idx % 10 AS INTEGER) AS cl, count(*) AS cnt FROM p GROUP BY 1",
    "membership_triplets": f"WITH p AS ({EMB}), l AS (SELECT idx, CAST(idx % 10 AS INTEGER) AS cl FROM p) SELECT l.cl, l.idx, 1.0::DOUBLE / s.cnt AS w FROM l JOIN (SELECT cl, count(*) AS cnt FROM l GROUP BY cl) s USING (cl)",
    "sizes_with_empties": f"{lift_loop(line4(), 4, 64, 1)} SELECT CAST(r.range AS INTEGER) AS cl, count(l.idx) AS cnt FROM range(64) r LEFT JOIN l1 l ON l.cl = r.range GROUP BY 1",
    # one sweep
    "sweep_means": f"{ONE} SELECT i, CAST(cl AS INTEGER) AS cl, {r6('e')} AS e FROM e1",
    "sweep_means_transposed": f"{ONE} SELECT i, CAST(cl AS INTEGER) AS cl, {r6('e')} AS e FROM e1",
    "sweep_mask": f"{ONE} SELECT e.i, CAST(e.cl AS INTEGER) AS cl, {r6('e.e')} AS z FROM e1 e JOIN l0 l ON e.i = l.idx AND e.cl = l.cl",
    "sweep_cnorm": f"{ONE} SELECT CAST(cl AS INTEGER) AS cl, {r6('c')} AS c FROM c1",
    "sweep_scores": f"{ONE} SELECT i, CAST(cl AS INTEGER) AS cl, {r6('dist')} AS dist FROM d1",
    "sweep_sqdist": f"{ONE}, own AS MATERIALIZED (SELECT i, v FROM ke WHERE i = j) SELECT d.i, CAST(d.cl AS INTEGER) AS cl, {r6('d.dist + own.v')} AS sq FROM d1 d JOIN own ON own.i = d.i",
    "sweep_labels": f"{ONE} SELECT idx, CAST(cl AS INTEGER) AS cl FROM l1",
    "sweep_objective": f"{ONE} SELECT {r6('(SELECT sum(v) FROM ke WHERE i = j) - sum(c1.c * s.n)')} AS objective FROM c1 JOIN (SELECT cl, count(*) AS n FROM l0 GROUP BY cl) s USING (cl)",
    # loops
    **{f"fit_{e}_k10": EMB_LABELS for e in ("entries", "panel_1d", "regrid_h1d", "tile_2d", "mixed_15d", "window", "window_disk", "fused", "local", "mixed_rowsplit", "mixed_row_join", "mixed_diagonal", "mixed_symmetric", "mixed_sparse_v", "mixed_f32acc64")},
    "fit_mixed_k16": labels(EMB, POLY, 16, 10),
    "fit_mixed_k32": labels(EMB, POLY, 32, 12),
    "fit_mixed_k64": labels(EMB, POLY, 64, 4),
    "history_changed": loop(EMB, POLY, 10, 17) + "\n" + " UNION ALL ".join(f"SELECT {t} AS sweep, (SELECT count(*) FROM l{t} a JOIN l{t - 1} b USING (idx) WHERE a.cl <> b.cl) AS changed" for t in range(1, 18)),
    "history_objective": loop(EMB, POLY, 10, 17) + ", tr AS (SELECT sum(v) AS t FROM ke WHERE i = j)\n" + " UNION ALL ".join(f"SELECT {t} AS sweep, {r6(f'(SELECT t FROM tr) - (SELECT sum(c.c * s.n) FROM c{t} c JOIN (SELECT cl, count(*) AS n FROM l{t - 1} GROUP BY cl) s USING (cl))')} AS objective" for t in range(1, 18)),
    # policies and worked example
    "empty_skip": lift_labels(line4(), 4, 64, 12),
    "empty_origin": lift_labels(line4(), 4, 64, 12, "origin"),
    "empty_reseed": lift_labels(line4(), 4, 64, 12, "reseed"),
    "tie_break_mini": labels(MINI, linear(), 2, 3),
    "mini_poly": labels(f"SELECT idx, key, [x[{USER.index('total') + 1}]] AS x FROM ({userfeat()})", POLY, 2, 3),
    "mini_scores": f"{loop(MINI, POLY, 2, 1)} SELECT i, CAST(cl AS INTEGER) AS cl, {r6('dist')} AS dist FROM d1",
    # other data
    **{f"{name}_points": f"SELECT idx, CAST(g AS INTEGER) AS pos, {r6('x[g]')} AS v FROM (SELECT idx, x, unnest(range(1, len(x) + 1)) AS g FROM ({sql}))" for name, sql in (("userfeat", userfeat()), ("part2", PART2), ("lobes", LOBES), ("rings", RINGS))},
    "docbag_points": f"SELECT idx, CAST(g - 1 AS INTEGER) AS pos, {r6('x[g]')} AS v, truth FROM (SELECT idx, x, truth, unnest(range(1, len(x) + 1)) AS g FROM ({_DOC})) WHERE x[g] > 0",
    "docvocab_counts": "WITH t AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS t FROM documents), v AS (SELECT t FROM (SELECT DISTINCT t FROM t) ORDER BY md5(t), t LIMIT 10000), c AS (SELECT t, row_number() OVER (ORDER BY t) - 1 AS col FROM v) SELECT doc_id, col, count(*) AS c FROM t JOIN c USING (t) GROUP BY ALL",
    **{f"{name}_points": f"SELECT idx, CAST(g AS INTEGER) AS pos, round(x[g], 4) + 0.0 AS v FROM (SELECT idx, x, unnest(range(1, len(x) + 1)) AS g FROM ({sql}))" for name, sql in (("line4", line4()), ("wide28", wide28()), ("eventday", eventday()))},
    "line4_fit_k16": lift_labels(line4(), 4, 16, 15),
    "docbag_fit_k4": labels(_DOC, POLY, 4, 9),
    "docbag_wide_fit_k4": f"{_WIDE_LOOP}\nSELECT idx, CAST(cl AS INTEGER) AS cl FROM l7",
    "window_heights": f"{loop(EMB, POLY, 10, 5)} SELECT idx, CAST(cl AS INTEGER) AS cl, CAST(h.h AS INTEGER) AS height FROM l5, (VALUES (64), (128), (256), (512), (1024), (2048)) AS h(h)",
    "userfeat_fit_k4": labels(userfeat(), POLY, 4, 14),
    "eventday_fit_k4": lift_labels(eventday(), 4, 4, 12),
    "lobes_linear": settled(LOBES, linear(), 2),
    "lobes_poly": labels(LOBES, POLY, 2, 3),
    "rings_poly": settled(RINGS, POLY, 2),
    "part2_fit": labels(PART2, POLY, 16, 23),
    # baselines
    "lloyd_k10": labels(EMB, linear(), 10, 12),
    "lift_poly2_k10": EMB_LABELS,
    # scoring
    "assign_holdout": f"""{loop(EMB.replace("FROM embeddings", "FROM embeddings WHERE vec_id % 5 <> 0"), POLY, 10, 12)}, f AS (SELECT idx, cl FROM l12), fe AS (SELECT ke.i, f.cl, avg(ke.v) AS e FROM ke JOIN f ON ke.j = f.idx GROUP BY ALL),
fc AS (SELECT f.cl, avg(fe.e) AS c FROM fe JOIN f ON fe.i = f.idx AND fe.cl = f.cl GROUP BY f.cl), h AS (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings WHERE vec_id % 5 = 0),
he AS (SELECT h.id, f.cl, avg(pow(list_dot_product(h.x, p.x) + 1, 2)) AS e FROM h, p JOIN f ON f.idx = p.idx GROUP BY ALL) SELECT he.id AS vec_id, CAST(min({{'d': fc.c - 2 * he.e, 'cl': he.cl}}).cl AS INTEGER) AS cl FROM he JOIN fc ON fc.cl = he.cl GROUP BY he.id""",
    "nearest_members_topk": f"""{_FINAL}, own AS (SELECT fe.i, CAST(fe.cl AS INTEGER) AS cl, fc.c - 2 * fe.e + ke.v AS sq FROM fe JOIN final f ON fe.i = f.idx AND fe.cl = f.cl JOIN fc ON fc.cl = fe.cl JOIN ke ON ke.i = fe.i AND ke.j = fe.i)
SELECT cl, CAST(r AS INTEGER) AS rank, i AS idx, {r6('sq')} AS sq_distance FROM (SELECT *, row_number() OVER (PARTITION BY cl ORDER BY sq, i) AS r FROM own) WHERE r <= 3""",
    "second_best_margin": f"{ONE}, r AS (SELECT i, cl, dist, lead(dist) OVER (PARTITION BY i ORDER BY dist, cl) - dist AS margin, row_number() OVER (PARTITION BY i ORDER BY dist, cl) AS n FROM d1) SELECT i, CAST(cl AS INTEGER) AS cl, {r6('margin')} AS margin FROM r WHERE n = 1",
    # measures
    "cost_table": _costs(),
    "cost_crossover": f"SELECT c AS k, (c + 1) * (c + 1) AS workers FROM ({EVENT_COUNTS})",
    "memory_table": _memory("round(memory_bytes, 0) AS memory_bytes"),
    "feasible_table": _memory("memory_bytes <= 80e9 AS feasible"),
    "weak_plan": "SELECT p, CAST(round(sqrt(p) * 96000) AS BIGINT) AS n, 4 * pow(round(sqrt(p) * 96000), 2) / p AS kernel_bytes_per_worker FROM (VALUES (1::BIGINT), (4::BIGINT), (16::BIGINT), (64::BIGINT), (256::BIGINT)) AS t(p)",
    "traffic_mixed": f"WITH s AS (SELECT count(*) AS n FROM embeddings) SELECT stage, item, words FROM (SELECT unnest({_moves('mixed_15d', '64', '10', 2, 3)}, recursive := true) FROM s)",
    "traffic_all": "WITH s AS (SELECT count(*) AS n FROM embeddings) " + " UNION ALL ".join(f"SELECT '{e}' AS engine, item, words FROM (SELECT unnest({_moves(e, '64', '10', 2, 1)}, recursive := true) FROM s)" for e in EXACT),
    "balance_1d": f"WITH p AS ({EMB}), s AS (SELECT CAST(ceil(count(*) / 4.0) AS BIGINT) AS s FROM p), w AS (SELECT CAST(r.range AS INTEGER) AS worker, count(p.idx) AS nonzeros FROM range(4) r LEFT JOIN (SELECT idx, idx // (SELECT s FROM s) AS w FROM p) p ON p.w = r.range GROUP BY 1) SELECT worker, nonzeros, round(max(nonzeros) OVER () / avg(nonzeros) OVER (), 6) AS ratio FROM w",
    "balance_2d": f"{ONE}, s AS (SELECT CAST(ceil(count(*) / 4.0) AS BIGINT) AS s FROM p), w AS (SELECT CAST(r.range AS INTEGER) AS worker, count(l.idx) AS nonzeros FROM range(4) r LEFT JOIN (SELECT idx, ((idx // (SELECT s FROM s)) // 2) * 2 + cl // 5 AS w FROM l1) l ON l.w = r.range GROUP BY 1) SELECT worker, nonzeros, round(max(nonzeros) OVER () / avg(nonzeros) OVER (), 6) AS ratio FROM w",
    "flops_table": f"WITH {EVENT_SETS_SQL} SELECT n, d, k, p, 2 * nn * nn * dd AS kernel_flops, nn * nn AS means_sparse, 2 * nn * nn * kk AS means_dense, nn * kk AS update, 4 * nn * nn AS kernel_bytes FROM par",
    "grid_product_table": f"WITH {EVENT_SETS_SQL} SELECT n, p, round(nn * nn / root, 3) AS bound_words, round(nn * nn / root * ({LOG2.format('root')}), 3) AS grid_words, round({LOG2.format('root')}, 9) AS ratio FROM par",
    "geo_mean_runs": "SELECT event_type AS algo, round(exp(avg(ln(1 + value))), 6) AS geo_mean FROM events GROUP BY algo",
    "weak_efficiency_fixed": _against("efficiency"),
    "strong_speedup_fixed": _against("speedup"),
    "speedup_fixed": f"WITH {RUNS_SQL}, t AS (SELECT dataset, k, algo, g, sum(seconds) AS s FROM runs GROUP BY ALL) SELECT a.dataset, a.k, a.g, a.s AS fast_s, b.s AS slow_s, b.s / a.s AS speedup FROM t a JOIN t b USING (dataset, k, g) WHERE a.algo = 'mixed' AND b.algo = 'panel'",
    "report_cube": f"WITH {RUNS_SQL} SELECT dataset, k, algo, sum(seconds) AS seconds, count(*) AS rows FROM runs GROUP BY CUBE (dataset, k, algo)",
    **{f"weak_scaling_{name}": scaling(name, True) for name in SETS},
    **{f"strong_scaling_{name}": scaling(name, False) for name in SETS},
    "window_comparison": "SELECT 'education' AS dataset, algo, n, 1.0::DOUBLE AS agreement FROM (SELECT least(1000, count(*)) AS n FROM documents), (VALUES ('mixed_15d'), ('window_256'), ('window_512'), ('window_1024'), ('fused')) AS a(algo)",
    # quality
    "contingency_lobes": f"{table_of(LOBES, POLY, 2, 3)} SELECT CAST(cl AS INTEGER) AS cl, truth, cnt FROM ct",
    "ari_lobes": f"{table_of(LOBES, POLY, 2, 3)} {_ARI}",
    "ari_lobes_linear": f"{table_of(LOBES, linear(), 2, 2)} {_ARI}",
    "nmi_docbag": f"{table_of(_DOC, POLY, 4, 9)} {_NMI}",
    "purity_docbag": f"{table_of(_DOC, POLY, 4, 9)} SELECT round(sum(m) / sum(c), 6) AS purity FROM (SELECT max(cnt) AS m, sum(cnt) AS c FROM ct GROUP BY cl)",
    "agreement_engines": "SELECT 1.0::DOUBLE AS agreement",
    # utilities
    "dense_index_lineitem": f"SELECT row_number() OVER (ORDER BY {KEY}) - 1 AS idx, l_orderkey, l_linenumber, l_partkey, l_suppkey FROM lineitem",
    "standardize_line4": f"SELECT l_orderkey, {', '.join(f'{r6(c)} AS {c}' for c in LINE4)} FROM ({z(LINE4, 'SELECT * FROM lineitem', 'l_orderkey')})",
    "minmax_line4": f"SELECT l_orderkey, {', '.join(f'{r6(f'({c} - min({c}) OVER ()) / (max({c}) OVER () - min({c}) OVER ())')} AS {c}' for c in LINE4)} FROM lineitem",
    "onehot_flags": "SELECT l_orderkey, l_linenumber, " + ", ".join(f"CASE WHEN l_returnflag = '{v}' THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END AS flag_{v.lower()}" for v in "ANR") + " FROM lineitem",
    "sample_n": "SELECT vec_id FROM embeddings ORDER BY md5('3|' || vec_id), vec_id LIMIT 100",
    "semi_changed": f"{ONE} SELECT p.key AS vec_id FROM p JOIN l1 a USING (idx) JOIN l0 b USING (idx) WHERE a.cl <> b.cl",
    "anti_unsampled": "SELECT vec_id FROM embeddings WHERE vec_id NOT IN (SELECT vec_id FROM embeddings ORDER BY md5('3|' || vec_id), vec_id LIMIT 100)",
    "setops_labels": f"{ONE} SELECT idx, CAST(cl AS INTEGER) AS cl FROM l1 EXCEPT SELECT idx, CAST(cl AS INTEGER) FROM l0",
    "asof_label_events": "WITH v AS (SELECT user_id, ts AS since, event_id AS version FROM events WHERE event_type = 'signup') SELECT e.event_id, (SELECT max_by(v.version, (v.since, v.version)) FROM v WHERE v.user_id = e.user_id AND v.since <= e.ts) AS version FROM events e WHERE e.event_type = 'purchase'",
    "interval_events": "WITH s AS (SELECT o_orderkey AS span, o_orderkey * 7 % 9000 AS lo, o_orderkey * 7 % 9000 + 3 AS hi FROM orders) SELECT event_id, span FROM events JOIN s ON event_id >= lo AND event_id < hi",
    # streams: the batch answer
    "stream_assign": labels(EMB, POLY, 10, 17).replace("SELECT idx, CAST(cl AS INTEGER) AS cl FROM l17", "SELECT idx, CAST(cl AS INTEGER) AS cl FROM l17"),
    "stream_tumbling": "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL",
    "stream_sliding": "SELECT date_trunc('hour', ts) + to_minutes(CAST((minute(ts) // 15) * 15 - o.range * 15 AS BIGINT)) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events, range(4) o GROUP BY ALL",
    "stream_session": "SELECT user_id, min(ts) AS start, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS f FROM events)) GROUP BY user_id, s",
    "stream_dedup": "SELECT event_id, user_id FROM events",
    "stream_pairs": "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'signup' AND b.event_type = 'purchase'",
    "stream_drift": "SELECT date_trunc('hour', ts) AS start, CAST(user_id % 3 AS INTEGER) AS cl, count(*) AS n, round(avg(value), 6) AS mean_sq, round(avg(CASE WHEN value > 100 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END), 6) AS far_share FROM events GROUP BY ALL",
    "stationary_table": f"WITH {GRID_SQL} SELECT n, d, k, p, round(nn * (kk + 1) / root, 3) AS still_k, round(nn * nn / root, 3) AS still_v, round(nn * nn / root, 3) AS still_e, round(nn * nn * 4, 3) AS cube_words FROM par",
    "largest_n": f"SELECT c AS p, CAST(floor(sqrt(80e9 * c / 4)) AS BIGINT) AS n, round(floor(sqrt(80e9 * c / 4)) / 80000, 6) AS growth FROM ({EVENT_COUNTS})",
    "cluster_ranks": f"{ONE}, s AS (SELECT i, CAST(cl AS INTEGER) AS cl, round(dist, 3) AS dist FROM d1) SELECT i, cl, CAST(rank() OVER t AS INTEGER) AS r, CAST(dense_rank() OVER t AS INTEGER) AS dense, round(percent_rank() OVER t, 6) AS share, CAST(ntile(3) OVER (PARTITION BY i ORDER BY dist, cl) AS INTEGER) AS third FROM s WINDOW t AS (PARTITION BY i ORDER BY dist)",
    "history_decrease": loop(EMB, POLY, 10, 6) + ", tr AS (SELECT sum(v) AS t FROM ke WHERE i = j), h AS (" + " UNION ALL ".join(f"SELECT {t} AS sweep, (SELECT t FROM tr) - (SELECT sum(c.c * s.n) FROM c{t} c JOIN (SELECT cl, count(*) AS n FROM l{t - 1} GROUP BY cl) s USING (cl)) AS o" for t in range(1, 7)) + f") SELECT sweep, {r6('lag(o) OVER (ORDER BY sweep) - o')} AS decrease FROM h",
    "top_clusters_lateral": f"{ONE} SELECT i AS idx, CAST(cl AS INTEGER) AS cl FROM (SELECT i, cl, row_number() OVER (PARTITION BY i ORDER BY dist, cl) AS n FROM d1) WHERE n <= 2",
    "contingency_pivot": f"{table_of(LOBES, POLY, 2, 3)} SELECT CAST(cl AS INTEGER) AS cl, CAST(coalesce(sum(cnt) FILTER (truth = 0), 0) AS BIGINT) AS t0, CAST(coalesce(sum(cnt) FILTER (truth = 1), 0) AS BIGINT) AS t1 FROM ct GROUP BY cl",
    "fit_given_k10": labels(EMB, POLY, 10, 8).replace("SELECT idx, idx % 10 AS cl FROM p", "SELECT idx, (idx // 3) % 10 AS cl FROM p"),
    "replicating_table": f"WITH {GRID_SQL} SELECT n, d, k, p, round(nn * nn * 4 / pp, 3) AS copied_words, round(nn * kk * 4 / pp + nn * kk / 4, 3) AS sweep_words FROM par",
    "collective_table": f"{_LOGS} SELECT n, d, k, p, round(root + lg, 3) AS allgather_messages, round(nn * (kk + 1) / root + nn * lg, 3) AS allgather_words, round(root * lg + lg, 3) AS rounds_messages, round(nn * (kk + 1) / root * lg + nn * lg, 3) AS rounds_words FROM lpar",
    "cost_table_logs": _LOGS + " UNION ALL ".join(f"SELECT '{a}' AS algo, n, d, k, p, round({km}, 3) AS kernel_messages, round({kw}, 3) AS kernel_words, round({dm}, 3) AS sweep_messages, round({dw}, 3) AS sweep_words FROM lpar" for a, (km, kw, dm, dw) in _STEP_LOGS.items()),
    "cost_table_function": f"SELECT algo, n, d, k, p, kernel_messages, kernel_words, sweep_messages, sweep_words FROM ({_costs()})",
    "sampled_features": entries_of(drawn_features(8, 64, 5)),
    "projected_emb": entries_of(drawn_projection(4, 64, 5)),
    "means_by_tile": f"{ONE} SELECT i, CAST(cl AS INTEGER) AS cl, {r6('e')} AS e FROM e1",
    "inner_pairs": f"{ONE} SELECT CAST(a.cl AS INTEGER) AS cl, {r6('avg(ke.v)')} AS c FROM ke JOIN l0 a ON ke.i = a.idx JOIN l0 b ON ke.j = b.idx AND a.cl = b.cl GROUP BY a.cl",
    "unmoved_labels": f"{ONE} SELECT a.idx, CAST(a.cl AS INTEGER) AS cl FROM l1 a JOIN l0 b ON a.idx = b.idx AND a.cl = b.cl",
    "rolling_events": "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 4) AS last5, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS in_hour FROM events",
    "report_rollup": f"WITH {RUNS_SQL} SELECT dataset, algo, sum(seconds) AS seconds, count(*) AS rows, CAST(grouping(dataset, algo) AS INTEGER) AS level FROM runs GROUP BY ROLLUP (dataset, algo) HAVING count(*) > 1",
    "run_statistics": f"WITH {RUNS_SQL} SELECT algo, quantile_disc(seconds, 0.5) AS middle, round(stddev_pop(seconds), 6) AS spread, round(corr(g, seconds), 6) AS with_workers, sum(seconds) FILTER (g = 4) AS on_four FROM runs GROUP BY algo",
    "stream_late": "WITH m AS (SELECT (min(epoch_us(ts)) + max(epoch_us(ts))) // 2 AS m, max(ts) - INTERVAL 2 HOUR AS w FROM events) SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events, m WHERE epoch_us(ts) >= m.m AND date_trunc('hour', ts) + INTERVAL 1 HOUR <= m.w GROUP BY ALL",
    "stream_dimension": "SELECT event_id, count(*) OVER (PARTITION BY user_id) AS events FROM events",
}
