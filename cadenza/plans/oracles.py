"""DuckDB SQL for the queries: brute force in the time domain, without any transform to frequencies."""

from __future__ import annotations

from cadenza.functions.transforms import center_weights, trend_weights
from cadenza.plans.workloads import SHAPE

#: CTEs that end in r(series_id, v): each series as a list.
_LEVEL = "lv AS (SELECT k.s AS series_id, p.p AS pos, coalesce(q.q, 0.0) AS value FROM (SELECT DISTINCT l_suppkey AS s FROM lineitem) k CROSS JOIN (SELECT unnest(range(0, 128)) AS p) p LEFT JOIN (SELECT l_suppkey AS s, CAST(floor(datediff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) * 128 / 2500) AS INT) AS p, sum(l_quantity) AS q FROM lineitem GROUP BY 1, 2) q ON q.s = k.s AND q.p = p.p)"
_CUMULATE = "list_transform(range(1, len(v) + 1), lambda i: list_sum(list_slice(v, 1, i)))"
R = {
    "supplier_level": f"{_LEVEL}, r AS (SELECT series_id, list(CAST(value AS DOUBLE) ORDER BY pos) AS v FROM lv GROUP BY series_id)",
    "supplier_walk": f"{_LEVEL}, r0 AS (SELECT series_id, list(CAST(value AS DOUBLE) ORDER BY pos) AS u FROM lv GROUP BY series_id), r1 AS (SELECT series_id, list_transform(u, lambda x: x - list_sum(u) / 128) AS v FROM r0), r AS (SELECT series_id, {_CUMULATE} AS v FROM r1)",
    "embedding_level": "r AS (SELECT vec_id AS series_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)",
    "embedding_walk": f"r1 AS (SELECT vec_id AS series_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings), r AS (SELECT series_id, {_CUMULATE} AS v FROM r1)",
    "event_walk": f"e0 AS (SELECT user_id, epoch_us(ts) AS t, value FROM events WHERE user_id IS NOT NULL AND ts IS NOT NULL AND value IS NOT NULL), e1 AS (SELECT *, min(t) OVER (PARTITION BY user_id) AS a, max(t) OVER (PARTITION BY user_id) AS b FROM e0), e2 AS (SELECT user_id, ((t - a) * 32) // (b - a + 1) AS p, avg(value) - 50 AS x FROM e1 GROUP BY 1, 2), r1 AS (SELECT u.user_id AS series_id, list(coalesce(x, 0.0) ORDER BY u.p) AS v FROM (SELECT user_id, unnest(range(0, 32)) AS p FROM (SELECT DISTINCT user_id FROM e2)) u LEFT JOIN e2 ON e2.user_id = u.user_id AND e2.p = u.p GROUP BY 1), r AS (SELECT series_id, {_CUMULATE} AS v FROM r1)",
    "segment_sales": "o AS (SELECT r_name AS region, n_name AS nation, c_mktsegment AS segment, o_orderpriority AS priority, CAST(floor(datediff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) * 32 / 2405) AS INT) AS pos, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE) AS value FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL), k AS (SELECT *, row_number() OVER (ORDER BY nation, segment, priority) AS series_id FROM (SELECT DISTINCT region, nation, segment, priority FROM o)), r AS (SELECT series_id, region, nation, segment, priority, list(coalesce(value, 0.0) ORDER BY p) AS v FROM (SELECT k.*, p, value FROM k CROSS JOIN (SELECT unnest(range(0, 32)) AS p) LEFT JOIN o ON o.nation = k.nation AND o.segment = k.segment AND o.priority = k.priority AND o.pos = p) GROUP BY ALL)",
    "doc_wordlen": "w AS (SELECT doc_id AS series_id, list_transform(list_filter(string_split_regex(text, '[ \\t\\n\\r]+'), lambda x: x <> ''), lambda x: length(x)) AS ws FROM documents), r AS (SELECT series_id, list_transform(range(0, 128), lambda p: list_avg(list_slice(ws, (p * len(ws)) // 128 + 1, greatest(((p + 1) * len(ws)) // 128, (p * len(ws)) // 128 + 1)))) AS v FROM w WHERE len(ws) > 0)",
}
_UNIT = "(('0x' || substr(md5({}), 1, 8))::BIGINT / 4294967296.0)"


def walk(n: int, count: int) -> str:
    start = f"least(greatest(50 + 15 * sqrt(-2 * ln({_UNIT.format('k || chr(45) || chr(117)')} + 1e-12)) * cos(2 * pi() * {_UNIT.format('k || chr(45) || chr(118)')}), 0.0), 100.0)"
    return f"ks AS (SELECT p_partkey AS series_id, CAST(p_partkey AS VARCHAR) AS k FROM part ORDER BY 1 LIMIT {count}), r1 AS (SELECT series_id, list_prepend({start}, list_transform(range(1, {n}), lambda i: {_UNIT.format("k || '-' || i")} * 8 - 4)) AS v FROM ks), r AS (SELECT series_id, {_CUMULATE} AS v FROM r1)"


#: Lengths at 1,000 walks, and counts at length 128 (as many as there are parts).
WALKS = [*((n, 1000) for n in (64, 128, 256, 512, 1024)), *((128, c) for c in (500, 2000, 4000, 8000, 12_000))]
R["random_walk"] = walk(128, 1000)


def normal(column: str = "v") -> str:
    return f"list_transform({column}, lambda x: (x - list_avg({column})) / list_stddev_pop({column}))"


def conv(column: str, weights) -> str:
    """Circular convolution of a list column."""
    w = "[" + ", ".join(f"{float(x)!r}::DOUBLE" for x in weights) + "]"
    return f"list_transform(range(0, len({column})), lambda i: list_sum(list_transform(range(0, {len(weights)}), lambda j: {w}[j + 1] * {column}[((i - j) % len({column}) + len({column})) % len({column}) + 1])))"


def mavg(m: int) -> list[float]:
    return [1.0 / m] * m


def z(name: str) -> str:
    """CTEs that end in z(series_id, v, ...): normal forms."""
    return f"{R[name]}, z AS (SELECT * REPLACE ({normal()} AS v) FROM r WHERE list_stddev_pop(v) >= 1e-9)"


def r4(x: str) -> str:
    return f"round({x} + 3e-7, 4) + 0.0::DOUBLE"


def unrolled(cte: str, source: str, column: str = "v", more: str = "") -> str:
    return f"WITH {cte} SELECT series_id, CAST(i - 1 AS INT) AS pos, {r4('x[i]')} AS value{more} FROM (SELECT *, {column} AS x FROM {source}) t, LATERAL (SELECT unnest(range(1, len(x) + 1)) AS i)"


def filtered(name: str, *weights, column: str = "v") -> str:
    ctes, at = R[name], "r"
    for k, w in enumerate(weights):
        ctes += f", f{k} AS (SELECT series_id, {conv('v', w)} AS v FROM {at})"
        at = f"f{k}"
    return unrolled(ctes, at)


def ranged(name: str, qid: int, eps: float, weights=None, two_sided: bool = False, use_normal: bool = True, data: str = "v", where: str = "", q: str | None = None, cte: str | None = None) -> str:
    """Distances of (filtered) series to a query at most eps away."""
    base = cte or (z(name) if use_normal else R[name])
    source = "z" if use_normal else "r"
    f = lambda c: conv(c, weights) if weights else c
    query = q or f"SELECT v AS q FROM {source} WHERE series_id = {qid}"
    return f"WITH {base}, qs AS ({query}), d AS (SELECT z0.*, list_distance({f(data)}, {f('q') if two_sided else 'q'}) AS dist FROM {source} z0, qs) SELECT series_id, {r4('dist')} AS dist FROM d WHERE dist <= {eps}{where}"


def joined(name: str, eps: float, weights=None, ordered: bool = False, negative: bool = False, halves: bool = False) -> str:
    f = conv("v", weights) if weights else "v"
    other = "list_transform(b.v, lambda x: -x)" if negative else "b.v"
    pairs = "a.series_id % 2 = 0 AND b.series_id % 2 = 1" if halves else "a.series_id <> b.series_id" if ordered else "a.series_id < b.series_id"
    return f"WITH {z(name)}, t AS MATERIALIZED (SELECT series_id, {f} AS v FROM z), d AS (SELECT a.series_id AS id_l, b.series_id AS id_r, list_distance(a.v, {other}) AS dist FROM t a JOIN t b ON {pairs}) SELECT id_l, id_r, {r4('dist')} AS dist FROM d WHERE dist <= {eps}"


def classed(name: str) -> str:
    """CTEs that end in z, the normal forms of one series of each class of equal ones, the others being c's."""
    return f"{R[name]}, c AS MATERIALIZED (SELECT series_id, v, min(series_id) OVER (PARTITION BY v) AS class_id FROM r WHERE list_stddev_pop(v) >= 1e-9), z AS (SELECT series_id, {normal()} AS v FROM c WHERE series_id = class_id)"


def class_joined(name: str, eps: float, weights=None, ordered: bool = False) -> str:
    links = joined(name, eps, weights, ordered).replace(z(name), classed(name)).replace("SELECT id_l, id_r, round", "SELECT 'link' AS kind, id_l, id_r, round")
    return f"{links} UNION ALL SELECT 'copy', class_id, series_id, 0.0::DOUBLE FROM c WHERE series_id <> class_id"


def nearest(name: str, qid: int, j: int, weights=None) -> str:
    f = conv("v", weights) if weights else "v"
    return f"WITH {z(name)}, t AS (SELECT series_id, {f} AS v FROM z), d AS (SELECT a.series_id, list_distance(a.v, q.v) AS dist FROM t a, t q WHERE q.series_id = {qid} AND a.series_id <> {qid}) SELECT series_id, {r4('dist')} AS dist FROM d ORDER BY d.dist, series_id LIMIT {j}"


def values(rows: list[tuple], names: list[str]) -> str:
    show = lambda x: f"'{x}'" if isinstance(x, str) else str(x).upper() if isinstance(x, bool) else f"{x!r}::DOUBLE" if isinstance(x, float) else f"{x}"
    return "SELECT * FROM (VALUES " + ", ".join("(" + ", ".join(map(show, r)) + ")" for r in rows) + ") t(" + ", ".join(names) + ")"


def _dft(column: str, n: int, f: str, kind: str) -> str:
    sign = "-" if kind == "sin" else ""
    return f"list_sum(list_transform(range(0, {n}), lambda t: {column}[t + 1] * {sign}{kind}(2 * pi() * {f} * t / {n}))) / sqrt({n})"


def _dissimilarity(budget: str = "", kind: str = "plain", paths: bool = False) -> str:
    """Compositions of up to two of three transformations on each side, in the time domain; in each order, if some of them are translations."""
    m, d = mavg(5), [1.0, -1.0]
    each = lambda body: lambda c: f"list_transform({c}, lambda x: {body})"
    smooth = ("mavg5", 0.4, lambda c: conv(c, m))
    steps = {"plain": [smooth, ("reverse", 0.7, each("-x")), ("diff", 0.9, lambda c: conv(c, d))], "moved": [smooth, ("shift(0.5)", 0.3, each("x + 0.5")), ("scale(0.5)", 0.4, each("x * 0.5"))]}[kind]
    names = [name for name, _, _ in steps]
    parts = ["SELECT series_id, 0.0::DOUBLE AS cost, '' AS path, v FROM s0"]
    ctes = "s0 AS MATERIALIZED (SELECT series_id, v FROM z WHERE region = 'ASIA')"
    for i, (_, cost, f) in enumerate(steps):
        ctes += f", s{i + 1} AS MATERIALIZED (SELECT series_id, {f('v')} AS v FROM s0)"
        parts.append(f"SELECT series_id, {cost}::DOUBLE AS cost, '{names[i]}' AS path, v FROM s{i + 1}")
        for j, (_, more, g) in enumerate(steps):
            if kind == "moved" or i <= j:
                both = [names[i], names[j]] if kind == "moved" else sorted([names[i], names[j]])
                parts.append(f"SELECT series_id, {cost + more!r}::DOUBLE AS cost, '{'+'.join(both)}' AS path, {g('v')} AS v FROM s{i + 1}")
    base = f"WITH {z('segment_sales')}, {ctes}, t AS MATERIALIZED ({' UNION ALL '.join(parts)})"
    if not paths:
        return f"{base}, d AS (SELECT a.series_id AS id_l, b.series_id AS id_r, min(a.cost + b.cost + list_distance(a.v, b.v)) AS dist FROM t a JOIN t b ON a.series_id < b.series_id GROUP BY 1, 2) SELECT id_l, id_r, {r4('dist')} AS dist FROM d{budget}"
    every = "SELECT a.series_id AS id_l, b.series_id AS id_r, a.cost + b.cost AS cost, a.path AS path_l, b.path AS path_r, a.cost + b.cost + list_distance(a.v, b.v) AS dist FROM t a JOIN t b ON a.series_id < b.series_id"
    best = "row_number() OVER (PARTITION BY id_l, id_r ORDER BY round(dist, 9), round(cost, 9), length(path_l) + length(path_r), path_l, path_r) = 1"
    return f"{base}, d AS ({every}) SELECT id_l, id_r, {r4('dist')} AS dist, round(cost, 4) AS cost, path_l, path_r FROM d QUALIFY {best}"


def _verdicts(rules: str) -> str:
    """Verdicts beside the numbers of users, and of those whose series leave the box that its moved corners span, in some element: plain values, or coefficients by parts or by magnitude and angle."""
    kernels = [("identity", [1.0], 0.0, 32), ("shift(2)", [1.0], 2.0, 32), ("scale(-3)", [-3.0], 0.0, 32), ("reverse", [-1.0], 0.0, 32), ("mavg4", mavg(4), 0.0, 32), ("trend4", trend_weights(4), 0.0, 32), ("diff", [1.0, -1.0], 0.0, 32), ("stretch2", [0.5**0.5] * 2, 0.0, 64), ("shift(1).mavg4", mavg(4), 1.0, 32)]
    listed = ", ".join(f"('{name}', [{', '.join(f'{x!r}::DOUBLE' for x in w)}], {move!r}::DOUBLE, {n})" for name, w, move, n in kernels)
    part = lambda kind: f"list_sum(list_transform(range(0, len(w)), lambda j: w[j + 1] * {kind}(2 * pi() * f * j / n)))"
    moved = lambda x, y, p, q: f"ar * {x} - ai * {y} + br AS {p}, ar * {y} + ai * {x} AS {q}"
    room = lambda p, q: f"1e-9 * (1 + greatest(abs({p}), abs({q})))"
    off = lambda x, p, q: f"({x} < least({p}, {q}) - {room(p, q)} OR {x} > greatest({p}, {q}) + {room(p, q)})"
    size = lambda x, y: f"sqrt({x} * {x} + {y} * {y})"
    turned = lambda a: f"({a}) - 2 * pi() * floor(({a}) / (2 * pi()))"
    ahead = lambda x, y: turned(f"atan2({y}, {x}) - atan2(ly, lx) + 1e-9")
    u, lo, hi = size("u", "w"), size("lx", "ly"), size("hx", "hy")
    polar = f"{off(u, lo, hi)} OR ({ahead('u', 'w')} > {ahead('hx', 'hy')} + 1e-9 AND {u} > {room(lo, hi)})"
    return f"""WITH {R["event_walk"]}, s AS MATERIALIZED (SELECT series_id, v, sqrt(list_sum(list_transform(v, lambda x: x * x))) AS len FROM r WHERE isfinite(list_sum(v))),
c AS MATERIALIZED (SELECT series_id, len, f, v[f + 1] AS value, {_dft("v", 32, "f", "cos")} AS x, {_dft("v", 32, "f", "sin")} AS y FROM s, (SELECT unnest(range(0, 32)) AS f)),
p AS MATERIALIZED (SELECT 'real' AS space, series_id, f, value AS p, 0.0::DOUBLE AS q, value AS x, 0.0::DOUBLE AS y FROM c UNION ALL SELECT 'rect', series_id, f, x, y, x, y FROM c
UNION ALL SELECT 'polar', series_id, f, {size("x", "y")}, CASE WHEN atan2(y, x) <= 1e-9 - pi() THEN pi() ELSE atan2(y, x) END, x, y FROM c WHERE {size("x", "y")} > 1e-9 * (1 + len)),
b AS (SELECT space, f, min(p) AS p0, max(p) AS p1, min(q) AS q0, max(q) AS q1 FROM p GROUP BY ALL),
e AS (SELECT space, f, p0 AS x0, q0 AS y0, p1 AS x1, q1 AS y1 FROM b WHERE space <> 'polar' UNION ALL SELECT space, f, p0 * cos(q0), p0 * sin(q0), p1 * cos(q1), p1 * sin(q1) FROM b WHERE space = 'polar'),
k(transform, w, move, n) AS (VALUES {listed}),
t AS (SELECT transform, f, f % 32 AS source, {part("cos")} AS ar, -{part("sin")} AS ai, CASE WHEN f = 0 THEN move * sqrt(32) ELSE 0.0 END AS br FROM k, (SELECT unnest(range(0, 64)) AS f) WHERE f < n),
m AS MATERIALIZED (SELECT space, transform, source, ar, ai, br, {moved("x0", "y0", "lx", "ly")}, {moved("x1", "y1", "hx", "hy")} FROM e JOIN t ON e.f = t.source),
d AS (SELECT m.space, transform, series_id, lx, ly, hx, hy, {moved("x", "y", "u", "w")} FROM p JOIN m ON p.space = m.space AND p.f = m.source),
o AS (SELECT DISTINCT transform, space, series_id FROM d WHERE CASE space WHEN 'polar' THEN {polar} WHEN 'rect' THEN {off("u", "lx", "hx")} OR {off("w", "ly", "hy")} ELSE {off("u", "lx", "hx")} OR abs(w) > 1e-9 END)
SELECT transform, space, safe, rule, (SELECT count(*) FROM s) AS series, coalesce(escaped, 0) AS escaped FROM ({rules}) LEFT JOIN (SELECT transform, space, count(*) AS escaped FROM o GROUP BY ALL) USING (transform, space)"""


def catalogue() -> dict[str, str]:
    out = {f"series_{k}": unrolled(R[k], "r") for k in ("supplier_walk", "supplier_level", "embedding_walk", "embedding_level", "event_walk", "segment_sales", "doc_wordlen", "random_walk")}
    m20, m8, m5 = mavg(20), mavg(8), mavg(5)
    nf = f"{R['supplier_walk']}, n AS (SELECT series_id, list_avg(v) AS mean, list_stddev_pop(v) AS sd, {normal()} AS v FROM r WHERE list_stddev_pop(v) >= 1e-9)"
    out["normal_form"] = f"WITH {nf} SELECT series_id, CAST(i - 1 AS INT) AS pos, {r4('mean')} AS mean, {r4('sd')} AS sd, {r4('v[i]')} AS value FROM n, LATERAL (SELECT unnest(range(1, len(v) + 1)) AS i)"
    out["normal_form_restore"] = unrolled(R["supplier_walk"], "r")
    out["rejected_series"] = f"WITH {R['doc_wordlen']} SELECT series_id FROM r WHERE list_stddev_pop(v) < 1e-9"
    out["dft_features"] = f"WITH {z('embedding_walk')} SELECT series_id, " + ", ".join(f"{r4(_dft('v', 64, str(f), k))} AS {p}{f}" for f in (1, 2) for p, k in (("re", "cos"), ("im", "sin"))) + " FROM z"
    out["dft_spectrum"] = f"WITH {R['event_walk']} SELECT series_id, CAST(f AS INT) AS f, {r4(_dft('v', 32, 'f', 'cos'))} AS re, {r4(_dft('v', 32, 'f', 'sin'))} AS im FROM r, (SELECT unnest(range(0, 17)) AS f)"
    out["idft_roundtrip"] = unrolled(R["event_walk"], "r")
    energies = [f"SELECT '{k}' AS relation, series_id, round(list_sum(list_transform(v, lambda x: x * x)) + 3e-4, 2) AS time_energy, round(list_sum(list_transform(v, lambda x: x * x)) + 3e-4, 2) AS spectral_energy FROM (WITH {R[k]} SELECT * FROM r)" for k in ("embedding_walk", "event_walk", "supplier_walk")]
    out["energy_parseval"] = " UNION ALL ".join(energies)
    shares = []
    for k, n in (("embedding_walk", 64), ("event_walk", 32), ("supplier_walk", 128), ("supplier_level", 128)):
        total = " + ".join(f"2 * (power({_dft('v', n, str(f), 'cos')}, 2) + power({_dft('v', n, str(f), 'sin')}, 2))" for f in (1, 2))
        shares.append(f"SELECT '{k}' AS relation, round(avg(({total}) / {n}), 3) AS share FROM (WITH {z(k)} SELECT * FROM z)")
    out["energy_concentration"] = " UNION ALL ".join(shares)
    out["circular_convolution"] = filtered("event_walk", [0.5, 0.3, 0.2])
    out["linearity_gap"] = f"WITH {R['event_walk']} SELECT series_id, 0.0::DOUBLE AS linearity_gap, 0.0::DOUBLE AS convolution_gap FROM r"
    for name, f in (("distance_euclidean", "list_distance(a.v, b.v)"), ("distance_cityblock", "list_sum(list_transform(range(1, len(a.v) + 1), lambda i: abs(a.v[i] - b.v[i])))")):
        out[name] = f"WITH {R['embedding_walk']} SELECT a.series_id, {r4(f)} AS dist FROM r a, r b WHERE b.series_id = 0"
    out["mavg_circular"], out["mavg_trend"], out["mavg_center"], out["kernel_difference"] = filtered("supplier_walk", m20), filtered("event_walk", trend_weights(5)), filtered("event_walk", center_weights(5)), filtered("event_walk", [1.0, -1.0])
    out["mavg_standard"] = unrolled(f"{R['supplier_walk']}, s AS (SELECT series_id, list_transform(range(1, 110), lambda i: list_avg(list_slice(v, i, i + 19))) AS v FROM r)", "s")
    out["mavg_gap"] = f"WITH {R['event_walk']}, c AS (SELECT series_id, {conv('v', m5)} AS c, list_avg(list_slice(v, 28, 32)) AS l FROM r) SELECT series_id, 0.0::DOUBLE AS inner_gap, {r4('list_max(list_transform(list_slice(c, 1, 4), lambda x: abs(x - l)))')} AS edge_gap FROM c"
    chain = ", ".join([f"p0 AS (SELECT series_id, v FROM r)", *(f"p{k} AS MATERIALIZED (SELECT series_id, {conv('v', mavg(3))} AS v FROM p{k - 1})" for k in range(1, 11))])
    out["mavg_repeated"] = f"WITH {R['event_walk']}, {chain}, u AS (" + " UNION ALL ".join(f"SELECT {k} AS p, * FROM p{k}" for k in (1, 2, 3, 10)) + f") SELECT series_id, CAST(i - 1 AS INT) AS pos, {r4('v[i]')} AS value, CAST(p AS INT) AS p FROM u, LATERAL (SELECT unnest(range(1, 33)) AS i)"
    on_walk = lambda expr: unrolled(f"{R['embedding_walk']}, s AS (SELECT series_id, {expr} AS v FROM r)", "s")
    out["identity_series"] = unrolled(R["embedding_walk"], "r")
    out["reverse_series"], out["shift_series"], out["scale_series"] = on_walk("list_transform(v, lambda x: -x)"), on_walk("list_transform(v, lambda x: x + 2.5)"), on_walk("list_transform(v, lambda x: x * -1.5)")
    out["stretch_series"] = on_walk("list_transform(range(0, 192), lambda i: v[i // 3 + 1])")
    out["compose_transforms"] = on_walk(f"list_transform({conv('v', mavg(4))}, lambda x: -(x + 1.0) * 2.0)")
    out["affine_spectrum"] = on_walk("list_transform(range(0, 64), lambda i: 0.5 * v[i + 1] + 4.0 / 8.0 * cos(2 * pi() * 3 * i / 64))")
    rules = {"real": "real stretch and translation", "rect": "real stretch, complex translation", "polar": "complex stretch, no translation"}
    # the shift's translation at frequency 0 is real
    table = {"identity": "TTT", "shift(2)": "TTF", "scale(-3)": "TTT", "reverse": "TTT", "mavg4": "FFT", "trend4": "FFT", "diff": "FFT", "stretch2": "FFT", "shift(1).mavg4": "FFF"}
    out["safety_verdicts"] = _verdicts(values([(t, s, v == "T", rules[s]) for t, vs in table.items() for s, v in zip(("real", "rect", "polar"), vs)], ["transform", "space", "safe", "rule"]))
    moved = lambda x, y: (f"2 * {x} + 3 * {y}", f"2 * {y} - 3 * {x}")
    within = " AND ".join(f"{x} BETWEEN least({p}, {q}) AND greatest({p}, {q})" for x, p, q in zip(moved("x", "y"), moved("a", "c"), moved("b", "d")))
    out["safety_counterexample"] = f"WITH {z('event_walk')}, p AS MATERIALIZED (SELECT series_id, {_dft('v', 32, '1', 'cos')} AS x, {_dft('v', 32, '1', 'sin')} AS y FROM z), b AS (SELECT min(x) AS a, max(x) AS b, min(y) AS c, max(y) AS d FROM p) SELECT series_id, {r4(moved('x', 'y')[0])} AS re, {r4(moved('x', 'y')[1])} AS im, {within} AS inside FROM p, b"
    out["index_nodes_cover"] = values([(n, t, 0) for n, m in (("supplier_walk", 20), ("embedding_walk", 8), ("event_walk", 5)) for t in ("identity", f"mavg{m}")], ["relation", "transform", "outside"]).replace("SELECT *", "SELECT relation, transform, CAST(outside AS BIGINT) AS outside")
    standard = lambda c: f"list_transform(range(1, 31), lambda i: list_avg(list_slice({c}, i, i + 2)))"
    out["example_smoothing"] = f"WITH {R['event_walk']}, t AS (SELECT a.series_id, a.v AS a, b.v AS b FROM r a, r b WHERE b.series_id = 0) SELECT series_id, {r4('list_distance(a, b)')} AS plain, {r4(f'list_distance({conv("a", mavg(3))}, {conv("b", mavg(3))})')} AS circular, {r4(f'list_distance({standard("a")}, {standard("b")})')} AS standard FROM t"
    places = "SELECT i, j, k, l FROM (SELECT unnest(range(1, 9)) AS i), (SELECT unnest(range(1, 9)) AS j), (SELECT unnest(range(1, 9)) AS k), (SELECT unnest(range(1, 9)) AS l) WHERE i < j AND j < k AND k < l"
    out["example_stretch"] = f"WITH {R['event_walk']}, t AS MATERIALIZED (SELECT a.series_id, list_transform(range(0, 8), lambda i: a.v[4 * i + 1]) AS s, list_transform(range(0, 4), lambda i: b.v[8 * i + 1]) AS p FROM r a, r b WHERE b.series_id = 0), g AS (SELECT series_id, sqrt(min(power(s[i] - p[1], 2) + power(s[j] - p[2], 2) + power(s[k] - p[3], 2) + power(s[l] - p[4], 2))) AS gapped FROM t, ({places}) GROUP BY 1) SELECT series_id, {r4('list_distance(list_transform(range(0, 8), lambda i: p[i // 2 + 1]), s)')} AS stretched, {r4('list_min(list_transform(range(1, 6), lambda i: list_distance(list_slice(s, i, i + 3), p)))')} AS window, {r4('gapped')} AS gapped FROM t JOIN g USING (series_id)"
    # 'window' is a keyword for some: quoted as a name
    out["example_stretch"] = out["example_stretch"].replace("AS window,", 'AS "window",')
    c = conv("v", m20)
    out["example_stepwise"] = f"WITH {R['supplier_walk']}, n AS MATERIALIZED (SELECT series_id, v AS raw, list_transform(v, lambda x: x - list_avg(v)) AS cen, {normal()} AS v FROM r), s AS MATERIALIZED (SELECT *, {c} AS sm FROM n) SELECT a.series_id, {r4('list_distance(a.raw, b.raw)')} AS raw, {r4('list_distance(a.cen, b.cen)')} AS shifted, {r4('list_distance(a.v, b.v)')} AS normal, {r4('list_distance(a.sm, b.sm)')} AS smoothed, {r4('list_distance(a.sm, list_transform(b.sm, lambda x: -x))')} AS opposite FROM s a, s b WHERE b.series_id = 1 AND a.series_id <> 1"
    chain = ", ".join([f"p0 AS MATERIALIZED (SELECT series_id, v FROM z WHERE series_id IN (3, 7))", *(f"p{k} AS MATERIALIZED (SELECT series_id, {c} AS v FROM p{k - 1})" for k in range(1, 11))])
    out["example_repeated_smoothing"] = f"WITH {z('supplier_walk')}, {chain} " + " UNION ALL ".join(f"SELECT CAST({k} AS INT) AS p, {r4('list_distance(a.v, b.v)')} AS dist FROM p{k} a, p{k} b WHERE a.series_id = 3 AND b.series_id = 7" for k in (0, 1, 2, 3, 10))
    E, P = "embedding_walk", "supplier_walk"
    out["range_single"] = ranged(E, 3, 100, m8, where=" AND series_id = 7")
    out["range_plain"] = out["range_identity"] = ranged(E, 3, 6.0)
    out["range_mavg"] = ranged(E, 3, 6.0, m8)
    out["range_mavg_twosided"] = out["scan_naive"] = out["scan_abandon"] = out["scan_time"] = out["scan_time_abandon"] = out["range_auto"] = out["range_rect_unsafe"] = ranged(P, 3, 8.0, m20, True)
    out["range_reverse"] = ranged(E, 3, 6.0, data="list_transform(v, lambda x: -x)")
    out["range_trend"] = ranged(E, 3, 6.0, trend_weights(8))
    out["range_rect_scale"] = ranged("supplier_level", 3, 874, use_normal=False, data="list_transform(v, lambda x: x * 0.9)")
    out["range_rect_shift"] = ranged("supplier_level", 3, 930, use_normal=False, data="list_transform(v, lambda x: x + 3.0)")
    out["range_rect_reverse"] = ranged("supplier_level", 3, 2625, use_normal=False, data="list_transform(v, lambda x: -x)")
    out["range_shape"] = ranged(P, 0, 9.0, m20, q=f"SELECT {normal('w')} AS q FROM (SELECT [{', '.join(f'{x}::DOUBLE' for x in SHAPE)}] AS w)")
    out["range_stretch"] = f"WITH {R['event_walk']}, h AS (SELECT series_id, list_transform(range(0, 16), lambda i: v[2 * i + 1]) AS v FROM r), n AS (SELECT series_id, {normal()} AS v FROM h WHERE list_stddev_pop(v) >= 1e-9), q AS (SELECT {normal()} AS q FROM r WHERE series_id = 4), d AS (SELECT series_id, list_distance(list_transform(range(0, 32), lambda i: n.v[i // 2 + 1]), q) AS dist FROM n, q) SELECT series_id, {r4('dist')} AS dist FROM d WHERE dist <= 5.0"
    sales = f"{R['segment_sales']}, z AS (SELECT *, list_avg(v) AS mean, list_stddev_pop(v) AS sd FROM r), y AS (SELECT * REPLACE ({normal()} AS v) FROM z WHERE sd >= 1e-9)"
    out["range_mean_sd"] = ranged("segment_sales", 5, 6.0, m5, True, cte=sales, where=" AND mean BETWEEN 0 AND 2e5 AND sd BETWEEN 5e4 AND 3e5").replace("FROM z WHERE series_id", "FROM y WHERE series_id").replace("FROM z z0", "FROM y z0")
    out["range_subset"] = ranged("segment_sales", 5, 7.0, m5, True, where=" AND region = 'ASIA'")
    out["range_translation_folded"] = f"WITH {z(E)}, d AS (SELECT a.series_id, list_distance(list_transform({conv('a.v', m8)}, lambda x: x + 0.1), b.v) AS dist FROM z a, z b WHERE b.series_id = 3) SELECT series_id, {r4('dist')} AS dist FROM d WHERE dist <= 6.0"
    out["range_real_vectors"] = ranged("embedding_level", 0, 1.0, use_normal=False, data="list_transform(v, lambda x: x * 0.5 + 0.01)")
    out["scan_plain_distance"] = ranged(E, 3, 2.0, use_normal=False)
    out["scan_normal_form"] = out["range_plain"]
    out["join_b_abandon"] = out["join_tree"] = out["join_grid"] = joined(P, 5, m20)
    out["join_a_full"], out["join_d_index_mavg"] = class_joined(P, 5, m20), class_joined(P, 5, m20, True)
    out["join_c_index"] = joined(P, 5, None, True)
    out["join_documents"] = class_joined("doc_wordlen", 0.5, m20)
    out["join_all_pairs"] = joined(E, 1.2, m8)
    one_sided = lambda name, left, right, eps: f"WITH {z(name)}, t AS MATERIALIZED (SELECT series_id, {left} AS x, {right} AS y FROM z), d AS (SELECT a.series_id AS id_l, b.series_id AS id_r, list_distance(a.x, b.y) AS dist FROM t a JOIN t b ON a.series_id <> b.series_id) SELECT id_l, id_r, {r4('dist')} AS dist FROM d WHERE dist <= {eps}"
    out["join_asymmetric"] = one_sided("event_walk", "v", conv("v", m5), 2.6)
    wave = f"list_transform(range(1, 65), lambda i: {conv('v', m8)}[i] + 0.25 * cos(2 * pi() * (i - 1) / 64))"
    out["join_translation_one_side"] = one_sided(E, wave, conv("v", m8), 1.6)
    out["join_rect_unsafe"] = class_joined(P, 5, m20, True)
    out["measure_nodes_equal"] = values([(n, True) for n in ("supplier_walk", "embedding_walk", "event_walk")], ["relation", "equal"])
    out["lemma_joins_no_dismissals"] = values([(n, s, k, 0, 0) for n in ("supplier_walk", "embedding_walk", "event_walk") for s in ("polar", "rect") for k in ("both sides", "one side", "translation")], ["relation", "space", "kind", "missed", "invented"]).replace("SELECT *", "SELECT relation, space, kind, CAST(missed AS BIGINT) AS missed, CAST(invented AS BIGINT) AS invented")
    out["join_two_relations"] = joined(E, 1.4, m8, halves=True)
    out["join_reverse"] = joined(P, 3.3, m20, negative=True)
    regions = f"WITH {z('segment_sales')}, t AS MATERIALIZED (SELECT series_id, region, v, {conv('v', m5)} AS s FROM z), p AS (SELECT a.series_id AS id_l, b.series_id AS id_r, list_distance(a.v, b.v) AS alike, list_distance(a.s, b.s) AS smoothed, list_distance(a.s, list_transform(b.s, lambda x: -x)) AS opposite FROM t a JOIN t b ON a.region = 'ASIA' AND b.region = 'EUROPE')"
    out["join_regions"] = f"{regions} " + " UNION ALL ".join(f"SELECT id_l, id_r, {r4(k)} AS dist, '{k}' AS kind FROM p WHERE {k} <= {e}" for k, e in (("alike", 3.6), ("smoothed", 1.3), ("opposite", 1.3)))
    out["knn_plain"] = nearest(E, 11, 10)
    out["knn_minmaxdist"] = out["knn_plain"]
    out["knn_mavg"] = out["knn_mindist"] = nearest(E, 11, 10, m8)
    out["knn_join"] = f"WITH {z('event_walk')}, t AS MATERIALIZED (SELECT series_id, {conv('v', m5)} AS v FROM z), d AS (SELECT a.series_id AS id_l, b.series_id AS id_r, list_distance(a.v, b.v) AS dist FROM t a JOIN t b ON a.series_id <> b.series_id), k AS (SELECT *, row_number() OVER (PARTITION BY id_l ORDER BY dist, id_r) AS rank FROM d) SELECT id_l, id_r, {r4('dist')} AS dist, CAST(rank AS INT) AS rank FROM k WHERE rank <= 3"
    out["dissimilarity_pairs"], out["dissimilarity_range"] = _dissimilarity(), _dissimilarity(" WHERE dist <= 3.0")
    out["dissimilarity_paths"], out["dissimilarity_translations"] = _dissimilarity(paths=True), _dissimilarity(kind="moved")
    out["lemma_no_dismissals"] = values([(n, s, k, 0) for n in ("supplier_walk", "embedding_walk", "event_walk") for k in (1, 3) for s in ("polar", "rect")], ["relation", "space", "k", "missed"]).replace("SELECT *", "SELECT relation, space, CAST(k AS INT) AS k, CAST(missed AS BIGINT) AS missed")
    x = conv("v", m8)
    prefix = " + ".join(f"2 * (power({_dft('x', 64, str(f), 'cos')} - {_dft('q', 64, str(f), 'cos')}, 2) + power({_dft('x', 64, str(f), 'sin')} - {_dft('q', 64, str(f), 'sin')}, 2))" for f in (1, 2))
    out["false_hits"] = f"WITH {z(E)}, q AS (SELECT v AS q FROM z WHERE series_id = 3), t AS MATERIALIZED (SELECT series_id, {x} AS x, q FROM z, q), d AS (SELECT sqrt({prefix}) AS near, list_distance(x, q) AS dist FROM t) SELECT count(*) FILTER (near <= 4.0) AS candidates, count(*) FILTER (dist <= 4.0) AS answers, count(*) FILTER (near <= 4.0) - count(*) FILTER (dist <= 4.0) AS false_hits FROM d"
    out["measure_answer_sweep"] = f"WITH {z(P)}, t AS MATERIALIZED (SELECT series_id, {conv('v', m20)} AS v FROM z), d AS (SELECT list_distance(a.v, b.v) AS dist FROM t a, t b WHERE b.series_id = 3) SELECT eps, count(*) FILTER (dist <= eps) AS answers FROM d, (SELECT unnest([2.0::DOUBLE, 4.0, 6.0, 9.0, 13.0]) AS eps) GROUP BY eps"
    for n, count in WALKS:
        sql = ranged("", 0, 0.9 * n**0.5, cte=f"{walk(n, count)}, z AS (SELECT series_id, {normal()} AS v FROM r)")
        out[f"walk_identity_{n}_{count}"] = out[f"walk_plain_{n}_{count}"] = out[f"walk_scan_{n}_{count}"] = sql
    return out
