"""DuckDB SQL that answers the queries from scratch: complete passes over the new graph, layer by layer."""

from __future__ import annotations

from graphrefresh import dense, relational, workloads
from graphrefresh.functions.weights import Map, dot, number
from graphrefresh.models import WIDTH, ZOO, Layer, Model, model
from graphrefresh.plans import verify
from graphrefresh.queries import ACTIVATIONS, CHUNKED, EDGES, FEATURES, GRAIN, NEW_ENDS, VERTICES, graph_of

H = [f"h{i}" for i in range(WIDTH)]

_BOTH = "SELECT a AS src, b AS dst, '{0}' AS rel, ts FROM ({2}) UNION ALL SELECT b, a, '{1}', ts FROM ({2})"
_ORDER_PART = _BOTH.format("contains", "in_order", "SELECT 4 * l_orderkey AS a, 4 * l_partkey + 1 AS b, min(l_shipdate) AS ts FROM lineitem GROUP BY 1, 2")
_PLACED = _BOTH.format("placed", "placed_by", "SELECT 4 * o_custkey + 2 AS a, 4 * o_orderkey AS b, min(o_orderdate) AS ts FROM orders GROUP BY 1, 2")
_K = "CAST(json_extract_string(props, '$.k') AS BIGINT)"
_LOW = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WHEN = "to_timestamp(1704067200 + floor(('0x' || substr(md5(concat_ws('-', 't', {0}, {1})), 1, 8))::BIGINT / 4294967296.0::DOUBLE * 31536000)::BIGINT)"
GRAPHS = {
    "knn": f"SELECT vec_id AS src, query AS dst, 'contains' AS rel, {_WHEN.format('vec_id', 'query')} AS ts FROM ({relational.ORACLES['topk_nearest']})",
    "doc_token": _BOTH.format("contains", "in_order", f"SELECT a, b, {_WHEN.format('a', 'b')} AS ts FROM (SELECT DISTINCT 2 * doc_id AS a, 2 * ('0x' || substr(md5(t), 1, 13))::BIGINT + 1 AS b FROM (SELECT doc_id, unnest(regexp_split_to_array({_LOW}, ' +')) AS t FROM documents) WHERE length(t) BETWEEN 3 AND 12)"),
    "turns": "SELECT DISTINCT conv_id * 1024 + turn AS src, conv_id * 1024 + nxt AS dst, 'contains' AS rel, to_timestamp(turn) AS ts FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) WHERE nxt IS NOT NULL",
    "order_part": _ORDER_PART,
    "cust_part": _BOTH.format("contains", "in_order", "SELECT 4 * o_custkey + 2 AS a, 4 * l_partkey + 1 AS b, min(o_orderdate) AS ts FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2"),
    "supp_part": _BOTH.format("contains", "in_order", "SELECT 4 * l_suppkey + 3 AS a, 4 * l_partkey + 1 AS b, min(l_shipdate) AS ts FROM lineitem GROUP BY 1, 2"),
    "copurchase": "SELECT 4 * x.l_partkey + 1 AS src, 4 * y.l_partkey + 1 AS dst, 'contains' AS rel, min(o_orderdate) AS ts FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey <> y.l_partkey JOIN orders ON o_orderkey = x.l_orderkey GROUP BY 1, 2",
    "typed": f"{_ORDER_PART} UNION ALL {_PLACED}",
    "transitions": f"SELECT k AS src, nxt AS dst, 'contains' AS rel, min(ts) AS ts FROM (SELECT {_K} AS k, lead({_K}) OVER (PARTITION BY user_id ORDER BY event_id) AS nxt, ts FROM events) WHERE nxt IS NOT NULL GROUP BY 1, 2",
    "user_item": _BOTH.format("contains", "in_order", f"SELECT 2 * user_id AS a, 2 * {_K} + 1 AS b, min(ts) AS ts FROM events GROUP BY 1, 2"),
}


def _share(*parts: str) -> str:
    return f"(('0x' || substr(md5(concat_ws('-', {', '.join(parts)})), 1, 8))::BIGINT / 4294967296.0)"


def _pair(tag: str) -> str:
    return _share(f"'{tag}'", "least(src, dst)", "greatest(src, dst)")


def _graph(name: str, shares: dict | None) -> str:
    """CTEs base, e (the new edges) and f (the new features)."""
    s = {"inserts": 0.0, "deletes": 0.0, "changes": 0.0, "removals": 0.0} | (shares or {})
    return f"""
all_e AS MATERIALIZED (SELECT src, dst, rel, ts, ((src + dst) % 4 + 1) / 4.0::DOUBLE AS w FROM ({GRAPHS[name]})),
at AS (SELECT quantile_disc(epoch_us(ts::TIMESTAMP), 0.9) AS cut FROM all_e),
base AS MATERIALIZED (SELECT src, dst, rel, w FROM all_e, at WHERE epoch_us(ts::TIMESTAMP) <= cut),
stream AS (SELECT src, dst, rel, w FROM all_e, at WHERE epoch_us(ts::TIMESTAMP) > cut),
ids AS (SELECT DISTINCT vid FROM (SELECT src AS vid FROM all_e UNION ALL SELECT dst FROM all_e)),
gone AS (SELECT vid FROM ids WHERE {_share("'v'", "vid")} < {s["removals"]}),
f AS (SELECT vid, (vid % 64) / 64.0::DOUBLE AS h0, (floor(vid / 3.0) % 16) / 16.0::DOUBLE AS h1, (vid % 7) / 8.0::DOUBLE + CASE WHEN {_share("'f'", "vid")} < {s["changes"]} THEN 0.5::DOUBLE ELSE 0 END AS h2, 1.0::DOUBLE AS h3 FROM ids WHERE vid NOT IN (FROM gone)),
e AS MATERIALIZED (SELECT * FROM (SELECT * FROM base WHERE NOT {_pair("d")} < {s["deletes"]} UNION ALL SELECT * FROM stream WHERE {_pair("i")} < {s["inserts"]}) WHERE src NOT IN (FROM gone) AND dst NOT IN (FROM gone)),
deg AS (SELECT dst AS vid, count(*)::DOUBLE AS deg FROM e GROUP BY dst)""".replace("\nat AS", "\ncut_at AS").replace("all_e, at ", "all_e, cut_at ")


def _mapped(rows: str, maps: tuple[Map, ...]) -> str:
    for m in maps:
        rows = f"(SELECT *, {', '.join(f'{dot([number(x) for x in row], [f'({i})' for i in m.inputs])} AS {c}' for row, c in zip(m.weights, m.outputs, strict=True))} FROM {rows})"
    return rows


def _layer(k: int, layer: Layer, below: str, edges: str = "e", width: int = WIDTH) -> str:
    rk = "rel" if layer.per_relation else "''"
    cols = lambda xs, p: ", ".join(f"{x} AS {p}{i}" for i, x in enumerate(xs))
    out = f"q{k} AS (SELECT vid AS src, {cols(layer.source, 'q')} FROM {_mapped(f'(SELECT h.*, coalesce(deg, 0.0) AS deg FROM {below} h LEFT JOIN deg USING (vid))', layer.source_maps)})"
    if layer.reads_target:
        out += f",\np{k} AS (SELECT vid AS dst, {cols(layer.target, 'p')} FROM {_mapped(below, layer.target_maps)})"
    out += f",\nc{k} AS (SELECT dst AS vid, {rk} AS rk, {cols(layer.message, 'c')} FROM {edges} JOIN q{k} USING (src)" + (f" JOIN p{k} USING (dst)" if layer.reads_target else "") + ")"
    out += f",\ns{k} AS (SELECT vid, rk, " + ", ".join(f"{layer.combine_by}(c{i}) AS s{i}" for i in range(layer.state_width)) + f" FROM c{k} GROUP BY vid, rk)"
    out += f",\nb{k} AS (SELECT vid, {cols(layer.finish, 'a')} FROM s{k})"
    out += f",\na{k} AS (SELECT vid, " + ", ".join(f"sum(a{i}) AS a{i}" for i in range(layer.sums)) + f" FROM b{k} GROUP BY vid)"
    rows = f"(SELECT h.vid, {', '.join(f'h.h{i}' for i in range(width))}, " + ", ".join(f"coalesce(a{i}, 0.0) AS a{i}" for i in range(layer.sums)) + f" FROM {below} h LEFT JOIN a{k} USING (vid))"
    return out + f",\nh_{k} AS MATERIALIZED (SELECT vid, {cols(layer.update, 'h')} FROM {_mapped(rows, layer.update_maps)})"


def _passes(m: Model, width: int = WIDTH) -> str:
    widths = [width, *[len(x.update) for x in m.layers]]
    return ",\n".join(_layer(k, x, "f" if k == 1 else f"h_{k - 1}", width=widths[k - 1]) for k, x in enumerate(m.layers, 1))


def _shown(width: int) -> str:
    return "vid, " + ", ".join(f"round(h{i} * {GRAIN}.0::DOUBLE) / {GRAIN}.0::DOUBLE + 0.0 AS d{i}" for i in range(width))


_SHOWN = _shown(WIDTH)


def whole(name: str, shares: dict | None = None, depth: int = 2) -> str:
    return f"WITH {_graph(graph_of(name), shares)},\n{_passes(model(name, depth))}\nSELECT {_SHOWN} FROM h_{depth}"


def new_ends(name: str) -> str:
    """The new graph with edges to unknown vertices, whose features are zeros."""
    rows = ", ".join(f"({a}, {b}, '{r}', {w}::DOUBLE)" for a, b, r, w in NEW_ENDS)
    ids = ", ".join(f"({v}, 0.0, 0.0, 0.0, 0.0)" for v in sorted({v for e in NEW_ENDS for v in e[:2] if v < 0}))
    graph = _graph("transitions", EDGES).replace("WHERE vid NOT IN (FROM gone)),", f"UNION ALL VALUES {ids}),", 1).replace("AND dst NOT IN (FROM gone))", f"AND dst NOT IN (FROM gone) UNION ALL VALUES {rows})", 1)
    return f"WITH {graph},\n{_passes(model(name))}\nSELECT {_SHOWN} FROM h_2"


def wide(kind: str, shares: dict | None = None, width: int = 64) -> str:
    changed = _share("'f'", "vec_id") + f" < {(shares or {}).get('changes', 0.0)}"
    x = ", ".join(f"round(embedding[{i + 1}]::DOUBLE * 64) / 64" + (f" + CASE WHEN {changed} THEN 0.5::DOUBLE ELSE 0 END" if i == 2 else "") + f" AS h{i}" for i in range(width))
    graph = _graph("knn", shares)
    a = graph.index("\nf AS (")
    graph = graph[:a] + f"\nf AS (SELECT vec_id AS vid, {x} FROM embeddings)," + graph[graph.index("\ne AS MATERIALIZED"):]
    return f"WITH {graph},\n{_passes(dense.dense_model(kind, dense.drawn_weights([width, 64, 64])), width)}\nSELECT {_shown(64)} FROM h_2"


def redundancy(graph: str) -> str:
    """Edges that each method processes for each of the hundred batches of a graph's newest tenth."""
    return f"""SELECT '{graph}' AS graph, batch, sum(n) FILTER (method = 'delta')::BIGINT AS delta, sum(n) FILTER (method = 'cache_reuse')::BIGINT AS cache_reuse, sum(n) FILTER (method = 'full_neighbour')::BIGINT AS full_neighbour FROM (
WITH t AS MATERIALIZED (SELECT src, dst, epoch_us(ts::TIMESTAMP) AS us FROM ({GRAPHS[graph]})), c AS (SELECT quantile_disc(us, 0.9) AS cut FROM t),
base AS MATERIALIZED (SELECT src, dst FROM t, c WHERE us <= cut), s AS (SELECT t.* FROM t, c WHERE us > cut),
m AS MATERIALIZED (SELECT src, dst, ((row_number() OVER (ORDER BY us, src, dst) - 1) * 100) // (SELECT count(*) FROM s) AS batch FROM s),
x1 AS MATERIALIZED (SELECT DISTINCT batch, dst AS vid FROM m), x2 AS MATERIALIZED (FROM x1 UNION SELECT batch, dst FROM x1 JOIN base ON src = vid),
y1 AS MATERIALIZED (SELECT batch, base.src AS vid FROM x2 JOIN base ON dst = vid UNION SELECT m.batch, m.src FROM x2 JOIN m ON m.batch = x2.batch AND dst = vid),
w AS (SELECT 'delta' AS method, batch, 2 * count(*) AS n FROM m GROUP BY 2 UNION ALL SELECT 'delta', batch, count(*) FROM x1 JOIN base ON src = vid GROUP BY 2
UNION ALL SELECT 'cache_reuse', batch, count(*) FROM (FROM x1 UNION ALL FROM x2) JOIN base ON dst = vid GROUP BY 2 UNION ALL SELECT 'cache_reuse', m.batch, count(*) FROM (FROM x1 UNION ALL FROM x2) x JOIN m ON m.batch = x.batch AND dst = vid GROUP BY 2
UNION ALL SELECT 'full_neighbour', batch, count(*) FROM (FROM x2 UNION ALL FROM y1) JOIN base ON dst = vid GROUP BY 2 UNION ALL SELECT 'full_neighbour', m.batch, count(*) FROM (FROM x2 UNION ALL FROM y1) x JOIN m ON m.batch = x.batch AND dst = vid GROUP BY 2)
FROM w) GROUP BY batch"""


def _moved(shares: dict) -> str:
    return f"(SELECT src, dst, rel FROM base WHERE {_pair('d')} < {shares['deletes']} UNION ALL SELECT src, dst, rel FROM stream WHERE {_pair('i')} < {shares['inserts']})"


def _reached(m: Model, shares: dict = FEATURES) -> str:
    """CTEs x_l: the vertices that a batch affects at layer l, by the rules for seeds, sources, readers and own terms."""
    out = ["x_0 AS (SELECT vid FROM f WHERE " + _share("'f'", "vid") + f" < {shares.get('changes', 0.0)})"]
    moved = _moved(shares)
    for k, layer in enumerate(m.layers, 1):
        touched = f"SELECT vid FROM x_{k - 1}" + (f" UNION SELECT dst FROM {moved}" if layer.reads_degree else "")
        own = f" UNION SELECT vid FROM x_{k - 1}" if layer.self_term or layer.reads_target else ""
        out.append(f"x_{k} AS MATERIALIZED (SELECT dst AS vid FROM {moved} UNION SELECT dst FROM e WHERE src IN ({touched}) UNION SELECT dst FROM base WHERE src IN ({touched}){own})")
    return ",\n".join(out)


def affected(name: str, queried: bool = False) -> str:
    m = model(name)
    where = f" AND {_share(chr(39) + 'q' + chr(39), 'vid')} < 0.2" if queried else ""
    return f"WITH {_graph(graph_of(name), FEATURES)},\n{_passes(m)},\n{_reached(m)}\nSELECT {_SHOWN} FROM h_2 WHERE vid IN (FROM x_2){where}"


def sampled(fanout: int) -> str:
    m = model("sage_mean")
    cut = lambda k: f"e{k} AS MATERIALIZED (SELECT src, dst, rel, w FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY {_share(chr(39) + f's{k - 1}' + chr(39), 'src', 'dst')}, src, rel) AS n FROM e) WHERE n <= {fanout})"
    layers = ",\n".join(f"{cut(k)},\n{_layer(k, x, 'f' if k == 1 else f'h_{k - 1}', f'e{k}')}" for k, x in enumerate(m.layers, 1))
    return f"WITH {_graph('order_part', FEATURES)},\n{layers},\n{_reached(m)}\nSELECT {_SHOWN} FROM h_2 WHERE vid IN (FROM x_2)"


def _traces(graph: str) -> str:
    """CTE t: method, layer, src, dst, rel of the distinct edges that each method processes for a two-layer mean model."""
    shares = {"inserts": 0.002, "deletes": 0.0002}
    some = lambda n, k: f"(SELECT src, dst, rel FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY {_share(chr(39) + f's{k - 1}' + chr(39), 'src', 'dst')}, src, rel) AS n FROM e) WHERE n <= {n})"
    row = lambda method, k, edges, where: f"SELECT '{method}' AS method, {k} AS layer, src, dst, rel FROM {edges} WHERE {where}"
    parts = [row("whole_graph", k, "e", "true") for k in (1, 2)]
    parts += [row("delta", k, "(SELECT src, dst, rel FROM base UNION SELECT src, dst, rel FROM e)", f"src IN (FROM x_{k - 1})") + f" UNION SELECT 'delta', {k}, src, dst, rel FROM {_moved(shares)}" for k in (1, 2)]
    parts += [row("cache_reuse", k, "e", f"dst IN (FROM x_{k})") for k in (1, 2)]
    for method, two, one in (("full_neighbour", "e", "e"), ("sampled_5", some(5, 2), some(5, 1)), ("sampled_10", some(10, 2), some(10, 1))):
        parts += [row(method, 2, two, "dst IN (FROM x_2)"), row(method, 1, one, f"dst IN (SELECT src FROM {two} WHERE dst IN (FROM x_2))")]
    every = " UNION ALL ".join(f"({p})" for p in parts)
    return f"WITH {_graph(graph, shares)},\n{_reached(model('sage_mean'), shares)},\nt AS MATERIALIZED (SELECT DISTINCT method, layer::INTEGER AS layer, src, dst, rel FROM ({every}))"


def _depth(depth: int) -> str:
    """Edges that each method processes in all layers of a mean model of that depth, for a small batch of changes."""
    shares, levels = workloads.FEW, range(1, depth + 1)
    need = [f"y_{depth} AS (FROM x_{depth})"] + [f"y_{k} AS MATERIALIZED (SELECT DISTINCT src AS vid FROM e WHERE dst IN (FROM y_{k + 1}))" for k in reversed(levels[:-1])]
    rows = [f"SELECT 'delta' AS method, {k} AS layer, src, dst, rel FROM (SELECT src, dst, rel FROM base UNION SELECT src, dst, rel FROM e) WHERE src IN (FROM x_{k - 1}) UNION SELECT 'delta', {k}, src, dst, rel FROM {_moved(shares)}" for k in levels]
    rows += [f"SELECT '{method}', {k}, src, dst, rel FROM e WHERE dst IN (FROM {at}_{k})" for method, at in (("cache_reuse", "x"), ("full_neighbour", "y")) for k in levels]
    every, found = " UNION ".join(f"({r})" for r in rows), ",\n".join(need)
    return f"SELECT {depth} AS depth, method, count(*) AS edges FROM (WITH {_graph('order_part', shares)},\n{_reached(model('sage_mean', depth), shares)},\n{found}\n{every}) GROUP BY 2"


_BANDS = f"""WITH d AS (SELECT dst AS vid, count(*) AS deg FROM ({_ORDER_PART}) GROUP BY dst
), p AS (SELECT deg, rank() OVER (ORDER BY deg DESC) - 1 AS above, count(*) OVER () AS n FROM d)
SELECT CASE WHEN above < 0.2 * n THEN 'top20' WHEN above < 0.5 * n THEN 'mid30' ELSE 'low50' END AS band, count(*) AS vertices, sum(deg)::BIGINT AS in_edges FROM p GROUP BY 1"""

_CHUNKS = f"""WITH e AS (SELECT src, dst FROM ({_ORDER_PART})
), d AS (SELECT dst, coalesce(sum(count(*)) OVER (ORDER BY dst ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // 8192 AS chunk FROM e GROUP BY dst
), o AS (SELECT DISTINCT src, chunk FROM e JOIN d USING (dst)
), l AS (SELECT chunk - lag(chunk) OVER (PARTITION BY src ORDER BY chunk) AS step FROM o)
SELECT count(*) AS loads, count(*) FILTER (step IS DISTINCT FROM 1) AS shared_loads FROM l"""

ORACLES: dict[str, str] = {f"graph_{n}": f"SELECT src, dst, rel, ((src + dst) % 4 + 1) / 4.0::DOUBLE AS w, epoch_us(ts::TIMESTAMP) AS us FROM ({q})" for n, q in GRAPHS.items()}
for _n in ZOO:
    ORACLES |= {f"full_{_n}": whole(_n), f"delta_{_n}_edges": whole(_n, EDGES), f"delta_{_n}_features": whole(_n, FEATURES)}
ORACLES |= {f"delta_{n}_vertex_ops": whole(n, VERTICES) for n in ("gin", "gcn", "gat", "rgcn")}
ORACLES |= {
    "full_unordered_gcn": whole("gcn"), "full_unordered_gat": whole("gat"), "delta_depth3_gin": whole("gin", FEATURES, 3), "delta_depth3_gat": whole("gat", FEATURES, 3), "delta_pruned": whole("gin", FEATURES),
    "delta_no_reorder": whole("gcn", FEATURES), "delta_contextual_gcn": whole("gcn", FEATURES), "delta_contextual_gat": whole("gat", FEATURES), "delta_evicted": whole("sage_mean", FEATURES),
    "delta_two_epochs_gin": whole("gin", FEATURES), "delta_two_epochs_gat": whole("gat", FEATURES), "whole_graph": whole("sage_mean", FEATURES), "periodic": whole("sage_mean"), "constmsg_fallback": whole("gat", FEATURES),
    "cachereuse_gcn": whole("gcn", FEATURES), "cachereuse_gat": whole("gat", FEATURES), "fullnbr_sage_mean": affected("sage_mean"), "fullnbr_gat": affected("gat"), "ondemand_gcn": affected("gcn", True), "ondemand_gat": affected("gat", True),
    "sampled_sage_k5": sampled(5), "sampled_sage_k10": sampled(10), "sampled_sage_k20": sampled(20), "degree_bands": _BANDS, "chunk_loads": _CHUNKS,
}
_T = _traces("order_part")
_TOTAL = ", n AS (SELECT method, count(*) AS edges FROM t GROUP BY 1), b AS (SELECT edges AS own FROM n WHERE method = 'delta')"
ORACLES |= {
    "edge_accesses": f"{_T} SELECT method, layer, count(*) AS edges FROM t GROUP BY 1, 2",
    "vertex_accesses": f"{_T} SELECT method, layer, count(DISTINCT vid) AS vertices FROM (SELECT method, layer, src AS vid FROM t UNION ALL SELECT method, layer, dst FROM t) GROUP BY 1, 2",
    "normalised_volume": f"{_T}{_TOTAL} SELECT method, edges, edges / own AS ratio FROM n, b",
    "redundant_share": f"{_T} SELECT t.method, count(*) FILTER (d.src IS NULL) / count(*) AS share FROM t LEFT JOIN (SELECT * FROM t WHERE method = 'delta') d USING (layer, src, dst, rel) GROUP BY 1",
    "affected_share": f"{_T} SELECT layer, count(*) / (SELECT count(*) FROM e) AS edge_share, any_value(v) / (SELECT count(*) FROM f) AS vertex_share FROM t JOIN (SELECT 1 AS layer, count(*) AS v FROM x_1 UNION ALL SELECT 2, count(*) FROM x_2) USING (layer) WHERE method = 'delta' GROUP BY 1",
    "delta_two_hop": f"WITH {_graph('transitions', EDGES)} SELECT a.src, b.dst, count(*) AS n FROM e a JOIN e b ON a.dst = b.src GROUP BY 1, 2",
    "sweep_depth": f"{_depth(2)} UNION ALL {_depth(3)}",
    "analytic_costs": f"WITH {_graph('order_part', workloads.SMALL)},\n{_reached(model('sage_mean'), workloads.SMALL)},\nn AS (SELECT (SELECT count(*) FROM base) / (SELECT count(*) FROM f) AS d, (SELECT count(*) FROM {_moved(workloads.SMALL)}) AS u, (SELECT count(*) FROM x_2) / (SELECT greatest(count(*), 1) FROM x_1) AS a) SELECT method, round(d * u * power(CASE WHEN method = 'sampled' THEN least(a, 5.0) ELSE a END, p), 3) AS edges FROM n, (VALUES ('delta', 3), ('cache_reuse', 4), ('full_neighbour', 5), ('sampled', 5)) v(method, p)",
    "sweep_chunk": " UNION ALL ".join(f"SELECT {n} AS max_edges, loads, shared_loads FROM ({_CHUNKS.replace('8192', str(n))})" for n in (512, 2048, 8192, 32768)),
}
_BAND = """, d AS (SELECT dst, count(*) AS deg FROM e GROUP BY 1), p AS (SELECT dst, rank() OVER (ORDER BY deg DESC) - 1 AS above, count(*) OVER () AS n FROM d)
, k AS (SELECT dst, CASE WHEN above < 0.2 * n THEN 'top20' WHEN above < 0.5 * n THEN 'mid30' ELSE 'low50' END AS band FROM p)
, v AS (SELECT band, count(*) FILTER (method = 'full_neighbour') - count(*) FILTER (method = 'delta') AS saved FROM t JOIN k USING (dst) WHERE method IN ('delta', 'full_neighbour') GROUP BY 1)
SELECT band, saved / sum(saved) OVER () AS share FROM v"""
ORACLES |= {
    "delta_evicted_sage_max": whole("sage_max", FEATURES), "delta_evicted_sage_min": whole("sage_min", FEATURES), "delta_evicted_gin": whole("gin", FEATURES), "delta_evicted_gat": whole("gat", FEATURES),
    "delta_new_vertices": new_ends("gcn"), "delta_new_vertices_gat": new_ends("gat"), "delta_agg_only_layout": whole("sage_mean", FEATURES), "delta_evicted_by_degree": whole("sage_mean", FEATURES),
    "redundancy_by_batch": " UNION ALL ".join(redundancy(g) for g in workloads.REDUNDANCY_GRAPHS),
    "volume_by_degree_band": _traces("cust_part") + _BAND,
    "state_bytes_by_layout": f"WITH {_graph('order_part', None)}, n AS (SELECT (SELECT count(*) FROM f) * 32 AS f, 2 * (SELECT count(DISTINCT dst) FROM base) * 40 AS a) SELECT 'features_only' AS layout, f::BIGINT AS bytes FROM n UNION ALL SELECT 'both', (f + 2 * f + a)::BIGINT FROM n UNION ALL SELECT 'sums_only', (f + a)::BIGINT FROM n",
}
_PASS = f"{{}},\n{_passes(model('rgcn'))}\nSELECT * FROM h_2"
_FAR = " + ".join(f"abs(n.h{i} - coalesce(o.h{i}, 0.0))" for i in range(WIDTH))
ORACLES |= {
    "scenario_recommendation": f"WITH {_graph('user_item', EDGES)},\n{_passes(model('sage_mean'))}\nSELECT {_SHOWN} FROM h_2 WHERE vid IN (SELECT src FROM stream WHERE {_pair('i')} < {EDGES['inserts']} AND src % 2 = 0)",
    "scenario_monitoring": f"SELECT * FROM (SELECT vid, round(({_FAR}) * {GRAIN}.0::DOUBLE) / {GRAIN}.0::DOUBLE AS moved FROM (WITH {_PASS.format(_graph('typed', EDGES))}) n LEFT JOIN (WITH {_PASS.format(_graph('typed', None))}) o USING (vid)) WHERE moved > 0",
    "drift_controlled": whole("gcn"),
    "activations": "SELECT vec_id, " + ", ".join(f"round({f('x')}, 6) AS {f.__name__}" for f in ACTIVATIONS) + " FROM (SELECT vec_id, embedding[1]::DOUBLE AS x FROM embeddings)",
    "embedding_difference": f"WITH {_graph('order_part', None)} SELECT 0.0::DOUBLE AS max_abs, 0.0::DOUBLE AS max_relative, 0::BIGINT AS mismatches, count(*) AS vertices FROM f",
    "chunk_sharing": _CHUNKS.partition("), l AS")[0] + ") SELECT a.chunk::BIGINT AS chunk_a, b.chunk::BIGINT AS chunk_b, count(*) AS shared FROM o a JOIN o b ON a.src = b.src AND b.chunk = a.chunk + 1 GROUP BY 1, 2",
    "constmsg_edges": f"{_T}, n AS (SELECT method, count(*) AS edges FROM t GROUP BY 1) SELECT m AS model, c AS constant_messages, n.edges AS edges, d.edges AS delta_edges FROM (VALUES ('sage_sum', true, 'delta'), ('sage_mean', false, 'cache_reuse')) v(m, c, method) JOIN n USING (method), (SELECT edges FROM n WHERE method = 'delta') d",
}
ORACLES |= {f"delta_chunked_{n}": whole(n, FEATURES) for n in CHUNKED} | {f"constmsg_{n}": whole(n, FEATURES) for n in ("sage_sum", "sage_mean", "gin", "gcn")}


def conditions(name: str) -> str:
    """The vector of least id that refutes each condition for a model."""
    layer = ZOO[name](1)
    part = lambda i: f"coalesce(embedding[{i} % greatest(coalesce(len(embedding), 0), 1) + 1]::DOUBLE, 0.0::DOUBLE)"
    value = lambda i: f"abs({part(i)}) + 0.0625::DOUBLE" if i % layer.state_width >= layer.sums else part(i)
    cols = ", ".join(f"{value(s * layer.state_width + i)} AS {p}{i}" for s, p in enumerate("xy") for i in range(layer.state_width))
    rows = [f"SELECT '{name}' AS model, '{c}' AS condition, min(trial) IS NULL AS holds, min(trial) AS counterexample FROM t WHERE {w}" for c, w in verify.refutations(layer, verify.Bound().tolerance).items()]
    return f"SELECT * FROM (WITH t AS (SELECT coalesce(vec_id, -1) AS trial, {cols} FROM embeddings) {' UNION ALL '.join(rows)})"


ORACLES["conditions_report"] = " UNION ALL ".join(conditions(_n) for _n in ZOO)
for _n in dense.KINDS:
    ORACLES |= {f"full_wide_{_n}": wide(_n), f"delta_wide_{_n}": wide(_n, FEATURES)}
ORACLES |= relational.ORACLES
