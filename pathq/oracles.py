"""DuckDB SQL for the queries of ``workloads``: plain recursion over (start, vertex, state) or plain joins, without caps or splits."""

from __future__ import annotations

from pathq.plans.automaton import compile_path
from pathq.sources.builders import KINDS


def _next(source: str, vertex: str, label: str, partition: str, order: str) -> str:
    over = f"OVER ({'PARTITION BY ' + partition + ' ' if partition else ''}ORDER BY {order})"
    return f"SELECT DISTINCT src, label, dst FROM (SELECT {vertex} AS src, {label} AS label, lead({vertex}) {over} AS dst FROM {source}) WHERE dst IS NOT NULL AND src IS NOT NULL AND label IS NOT NULL"


def _typed(kind: str, key: str) -> str:
    return f"{key}::BIGINT * {len(KINDS)} + {KINDS.index(kind)}"


def _fk(table: str, a: tuple[str, str], b: tuple[str, str], label: str) -> str:
    return f"SELECT {_typed(*a)} AS src, '{label}' AS label, {_typed(*b)} AS dst FROM {table}"


def handoff(t: int) -> str:
    return _next(f"(SELECT * FROM orders WHERE o_totalprice > {t})", "o_custkey", "o_orderpriority", "", "o_orderdate, o_orderkey")


def relay(t: int) -> str:
    return _next(f"(SELECT * FROM events WHERE value > {t})", "user_id", "event_type", "", "ts, event_id")


def partchain(q: int) -> str:
    return _next(f"(SELECT * FROM lineitem WHERE l_quantity >= {q})", "l_partkey", "l_returnflag", "l_orderkey", "l_linenumber, l_partkey, l_suppkey, l_shipdate")


FLOW = _next("events", "event_id", "event_type", "user_id", "ts, event_id")
TURNS = _next("conversations", "conv_id * 1000 + turn", "role", "conv_id", "turn")
WALK = _next("(SELECT * FROM orders WHERE o_totalprice > 450000 AND o_orderpriority = '1-URGENT')", "o_custkey", "'x'", "", "o_orderdate, o_orderkey")
COMMERCE = "SELECT DISTINCT src, label, dst FROM (" + " UNION ALL ".join(
    [
        _fk("orders", ("customer", "o_custkey"), ("order", "o_orderkey"), "placed"),
        _fk("lineitem", ("order", "l_orderkey"), ("part", "l_partkey"), "contains"),
        _fk("lineitem", ("part", "l_partkey"), ("supplier", "l_suppkey"), "from"),
        _fk("customer", ("customer", "c_custkey"), ("nation", "c_nationkey"), "lives"),
        _fk("supplier", ("supplier", "s_suppkey"), ("nation", "s_nationkey"), "based"),
        _fk("nation", ("nation", "n_nationkey"), ("region", "n_regionkey"), "in"),
    ]
) + ") WHERE src IS NOT NULL AND dst IS NOT NULL"
NEAR = """SELECT src, label, dst FROM (
  SELECT a.vec_id AS src, CASE WHEN a.label = b.label THEN 'same' ELSE 'cross' END AS label, b.vec_id AS dst,
         row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) DESC, b.vec_id) AS k
  FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE k <= 3"""
COPY = "SELECT d.doc_id AS src, 'copy' AS label, f.first AS dst FROM documents d JOIN (SELECT coalesce(text, '') AS t, min(doc_id) AS first FROM documents GROUP BY ALL) f ON coalesce(d.text, '') = f.t WHERE d.doc_id <> f.first"
QUOTES = "SELECT DISTINCT d.doc_id * 2 AS src, 'quotes' AS label, b.item_id * 2 + 1 AS dst FROM documents d JOIN benchmark b ON contains(d.text, b.text) WHERE b.text <> ''"

SHORT = "1-URGENT 3-MEDIUM* 5-LOW"


def walk(graph: str, expr: str, vertices: str | None = None, where: str = "") -> str:
    """CTEs g, tr, walk (s, v, q) from every vertex that has an edge; and ``vertices`` for the empty path."""
    a = compile_path(expr)
    (first,) = a.initial
    rows = ", ".join(f"({q}, '{s.label}', {p}, {str(s.backward).lower()})" for q, s, p in sorted(a.transitions, key=lambda t: (t[0], t[1].label, t[2])))
    last = ", ".join(map(str, sorted(a.accepting)))
    return f"""g AS ({graph}),
tr(q, label, p, turned) AS (VALUES {rows}),
move AS (SELECT DISTINCT CASE WHEN turned THEN dst ELSE src END AS a, q, CASE WHEN turned THEN src ELSE dst END AS b, p FROM g JOIN tr ON g.label = tr.label),
walk(s, v, q) AS (
  SELECT DISTINCT a, a, q FROM move WHERE q = {first} {where}
  UNION
  SELECT s, b, p FROM walk JOIN move ON v = a AND walk.q = move.q),
found AS (SELECT DISTINCT s AS src, v AS dst FROM walk WHERE q IN ({last}){f" UNION SELECT id, id FROM ({vertices})" if a.nullable else ""})"""


def answers(graph: str, expr: str, vertices: str | None = None, tail: str = "SELECT src, dst FROM found") -> str:
    if vertices is None:
        vertices = f"SELECT src AS id FROM ({graph}) UNION SELECT dst FROM ({graph})"
    return f"WITH RECURSIVE {walk(graph, expr, vertices)}\n{tail}"


def words(graph: str, *labels: str) -> str:
    """Joins for one word; ^ turns an edge."""
    parts, on = [], []
    for i, label in enumerate(labels):
        a, b = ("dst", "src") if label[0] == "^" else ("src", "dst")
        parts.append(f"(SELECT {a} AS p, {b} AS q FROM g WHERE label = '{label.lstrip('^')}') r{i}")
        if i:
            on.append(f"r{i - 1}.q = r{i}.p")
    return f"SELECT DISTINCT r0.p AS src, r{len(labels) - 1}.q AS dst FROM {', '.join(parts)}{' WHERE ' + ' AND '.join(on) if on else ''}"


def word(graph: str, *labels: str) -> str:
    return f"WITH g AS ({graph}) {words(graph, *labels)}"


def _n() -> tuple[int, int]:
    a = compile_path(SHORT)
    (first,) = a.initial
    return a.n_states, first


N, FIRST = _n()
H300, H325, H350, H400, H450 = map(handoff, (300_000, 325_000, 350_000, 400_000, 450_000))
URGENT = f"SELECT DISTINCT src, 'x' AS label, dst FROM ({H350}) WHERE label = '1-URGENT'"
LINKS = "SELECT DISTINCT page_id * 2 AS src, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS target FROM pages"
LAST = ", ".join(map(str, sorted(compile_path(SHORT).accepting)))
NONE = "SELECT 1 AS id WHERE false"


def lists(graph: str, cap: str = "(SELECT cap FROM capped)") -> str:
    """Ends per middle vertex of a hand-off graph, as the automaton has them: packed vertex, count, count up to the cap, class."""
    n = compile_path(SHORT).n_states
    return f"""{walk(graph, SHORT, NONE)},
capped AS (SELECT canonical_edges, floor(sqrt(canonical_edges))::BIGINT + 1 AS cap FROM (SELECT (SELECT count(*) FROM move)
  + (SELECT count(*) FROM (SELECT DISTINCT a, q FROM move WHERE q = {FIRST})) + (SELECT count(*) FROM (SELECT DISTINCT b, p FROM move WHERE p IN ({LAST}))) AS canonical_edges)),
ends AS (SELECT DISTINCT b AS v, p AS q FROM move WHERE p IN ({LAST})),
rear(y, v, q) AS (SELECT v, v, q FROM ends UNION SELECT y, a, move.q FROM rear JOIN move ON v = b AND rear.q = p),
deg AS (SELECT v * {n} + q AS x, count(*) AS d FROM rear GROUP BY ALL),
listed AS (SELECT x, d, least(d, {cap})::BIGINT AS deg, d >= {cap} AS heavy FROM deg)"""


def split(tail: str, graph: str | None = None, cap: str = "(SELECT cap FROM capped)") -> str:
    return f"WITH RECURSIVE {lists(graph or H325, cap)}\n{tail}"


HEAVY_START = f"SELECT (x - {FIRST}) // {N} AS s FROM listed WHERE heavy AND x % {N} = {FIRST} AND x IN (SELECT a * {N} + q FROM move)"

SIZES = {
    "handoff_split": (H300, SHORT),
    "handoff_sparse": (H400, SHORT),
    "flow_funnel": (FLOW, "view (view|click)* purchase"),
    "flow_until_purchase": (FLOW, "(view|click|signup|error)* purchase"),
    "flow_dead_end": (FLOW, "(view|click|signup|purchase|error)* refund"),
    "relay_dense": (relay(100), "view click* purchase"),
    "relay_sparse": (relay(150), "view click* purchase"),
    "partchain_small": (partchain(40), "R N* A"),
}
SWEEP = {
    "handoff 300k": (H300, SHORT),
    "handoff 350k": (H350, SHORT),
    "handoff 400k": (H400, SHORT),
    "partchain 36": (partchain(36), "R N* A"),
    "partchain 40": (partchain(40), "R N* A"),
    "relay 100": (relay(100), "view click* purchase"),
    "relay 150": (relay(150), "view click* purchase"),
}
ALL_EVENTS = "SELECT event_id AS id FROM events"


def sized(name: str, graph: str, expr: str) -> str:
    """A row of one graph and query: v, e after dropping labels that the query lacks (vertices before), o answers, and looks of
    the forward and backward search and of complete lists."""
    a = compile_path(expr)
    labels = ", ".join(f"'{x}'" for x in sorted({s.label for _, s, _ in a.transitions}))
    last = ", ".join(map(str, sorted(a.accepting)))
    vertices = ALL_EVENTS if graph == FLOW else f"SELECT src AS id FROM ({graph}) UNION SELECT dst FROM ({graph})"
    return f"""(WITH RECURSIVE {walk(graph, expr, NONE)},
rear(y, v, q) AS (SELECT DISTINCT b, b, p FROM move WHERE p IN ({last}) UNION SELECT y, a, move.q FROM rear JOIN move ON v = b AND rear.q = p),
deg AS (SELECT v, q, count(*) AS d FROM rear GROUP BY ALL),
canon AS (SELECT (SELECT count(*) FROM move) + (SELECT count(*) FROM (SELECT DISTINCT a, q FROM move WHERE q IN ({", ".join(map(str, sorted(a.initial)))}))) + (SELECT count(*) FROM (SELECT DISTINCT b, p FROM move WHERE p IN ({last}))) AS n)
SELECT '{name}' AS name, (SELECT count(DISTINCT id) FROM ({vertices}))::DOUBLE AS v, (SELECT count(*) FROM g WHERE label IN ({labels}))::DOUBLE AS e, (SELECT count(*) FROM found)::DOUBLE AS o,
  (SELECT count(*) FROM walk JOIN move ON v = a AND walk.q = move.q)::BIGINT AS forward, (SELECT count(*) FROM rear JOIN move ON v = b AND rear.q = p)::BIGINT AS lists,
  (SELECT count(*) FROM (SELECT DISTINCT y, v, q FROM rear) r JOIN move ON r.v = b AND r.q = p)::BIGINT AS backward,
  coalesce((SELECT max(d) FROM deg), 0) >= floor(sqrt((SELECT n FROM canon))) + 1 AS filled)"""


def sizes(columns: str, of: dict[str, tuple[str, str]] = SIZES) -> str:
    return f"WITH z AS ({' UNION ALL '.join(f'SELECT * FROM {sized(n, *x)}' for n, x in of.items())}) SELECT {columns} FROM z"


def _delta(rec: str) -> str:
    return f"WITH RECURSIVE e AS (SELECT src, dst FROM ({URGENT})), {rec}"


CLOSED = "t(src, dst) AS (SELECT src, dst FROM e UNION SELECT t.src, e.dst FROM t JOIN e ON t.dst = e.src)"


def _hops(limit: int = 64) -> str:
    return f"t(src, dst, h) AS (SELECT src, dst, 0 FROM e UNION SELECT t.src, e.dst, h + 1 FROM t JOIN e ON t.dst = e.src WHERE h < {limit})"


EVENT_VERTICES = "SELECT event_id AS id FROM events"
CHAT_VERTICES = "SELECT conv_id * 1000 + turn AS id FROM conversations"
EXPECTED_EXAMPLE = "(0, 'd', 0, true, true, true), (0, 'e', 1, true, true, false), (0, 'g', 2, true, true, true), (1, 'f', 2, false, false, true), (2, 'e', 1, false, true, false), (2, 'g', 2, false, true, true)"
NATION = f"""WITH RECURSIVE {walk(H400, SHORT, "SELECT 1 AS id WHERE false")},
wide AS (SELECT f.src, f.dst, n.n_regionkey::BIGINT AS region, c.c_nationkey::BIGINT AS nation FROM found f JOIN customer c ON c.c_custkey = f.src JOIN nation n ON n.n_nationkey = c.c_nationkey)"""
OTHER = "1-URGENT 2-HIGH* 5-LOW"


def both(tail: str) -> str:
    return f"WITH one AS ({answers(H350, SHORT)}), two AS ({answers(H350, OTHER)}), three AS ({answers(H350, '2-HIGH*')}) {tail}"


SPARSE, MIXED = answers(H400, SHORT), answers(H350, SHORT)


def segment(column: str, name: str) -> str:
    return f"{column} IN (SELECT c_custkey FROM customer WHERE c_mktsegment = '{name}')"


def windows(starts: str) -> str:
    """Answers of the funnel in every window's own graph: events of a user in one window, each leading to the next."""
    return f"""WITH RECURSIVE e AS (SELECT *, epoch_us(ts) AS us FROM events), w AS ({starts}),
n AS (SELECT start, user_id, event_id, event_type, lead(event_id) OVER (PARTITION BY start, user_id ORDER BY ts, event_id) AS nxt FROM w),
m AS (SELECT * FROM n WHERE nxt IS NOT NULL),
t(start, user_id, s, v, q) AS (
  SELECT start, user_id, event_id, nxt, 1 FROM m WHERE event_type = 'view'
  UNION SELECT t.start, t.user_id, s, nxt, CASE WHEN event_type = 'purchase' THEN 2 ELSE 1 END FROM t JOIN m ON t.start = m.start AND t.user_id = m.user_id AND v = m.event_id AND q = 1 AND event_type IN ('view', 'click', 'purchase'))
SELECT DISTINCT start::BIGINT AS start, user_id, s AS src, v AS dst FROM t WHERE q = 2"""


REPORTED = f"""SELECT (SELECT count(*) FROM (SELECT src FROM g UNION SELECT dst FROM g))::BIGINT AS n_vertices, (SELECT count(*) FROM g WHERE label IN (SELECT label FROM tr))::BIGINT AS n_edges,
  (SELECT count(DISTINCT label) FROM tr)::BIGINT AS n_labels, (SELECT count(*) FROM found)::BIGINT AS out,
  (SELECT count(*) FROM (SELECT a, q FROM move UNION SELECT b, p FROM move))::BIGINT AS product_vertices, (SELECT count(*) FROM move)::BIGINT AS product_edges, canonical_edges::BIGINT AS canonical_edges, cap,
  (SELECT sum(deg) FROM listed)::BIGINT AS reach_rows, (SELECT count(*) FROM listed WHERE NOT heavy)::BIGINT AS n_light, (SELECT count(*) FROM listed WHERE heavy)::BIGINT AS n_heavy,
  (SELECT count(*) FROM (SELECT a, q FROM move UNION SELECT b, p FROM move))::BIGINT - (SELECT count(*) FROM listed)::BIGINT AS n_absent,
  (SELECT count(*) FROM hs)::BIGINT AS heavy_sources, (SELECT count(*) FROM found WHERE src NOT IN (SELECT s FROM hs))::BIGINT AS light_rows, (SELECT count(*) FROM found WHERE src IN (SELECT s FROM hs))::BIGINT AS heavy_rows,
  (SELECT count(*) FROM walk WHERE s IN (SELECT s FROM hs))::BIGINT AS trail_rows, (SELECT count(*) FROM walk JOIN move ON v = a AND walk.q = move.q WHERE s IN (SELECT s FROM hs))::BIGINT AS inspect_trail
FROM capped"""
LOW = "(SELECT * FROM events WHERE (props::JSON->>'k')::INT < 50)"
HIDDEN = "(SELECT *, CASE WHEN o_orderstatus <> 'P' THEN o_custkey END AS who FROM orders)"
EVEN_LINKS = f"e AS ({LINKS}), t(a, b) AS (SELECT x.src, y.src FROM e x JOIN e y USING (target) UNION SELECT t.a, y.src FROM t JOIN e x ON t.b = x.src JOIN e y USING (target))"
RINGS = """SELECT (SELECT count(*) FROM customer)::BIGINT AS n_vertices, (SELECT 2 * count(*) FROM customer)::BIGINT AS n_edges, 0::BIGINT AS out"""
CLOSURE_OF = f"WITH RECURSIVE e AS (SELECT src, dst FROM ({H300}) WHERE label = '1-URGENT'), t(src, dst) AS (SELECT src, dst FROM e UNION SELECT t.src, e.dst FROM t JOIN e ON t.dst = e.src) "

LETTERS = {"view": "d", "click": "e", "signup": "f", "purchase": "g", "error": "h"}
PLAIN = {"view": "a", "click": "b", "purchase": "c", "error": "d"}


def _lettered(letters: dict[str, str]) -> str:
    """Events that have a letter, with it."""
    cases = " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in letters.items())
    return f"(SELECT * FROM (SELECT *, CASE event_type {cases} END AS letter FROM events) WHERE letter IS NOT NULL)"


ORACLES: dict[str, str] = {
    "handoff_split": answers(H300, SHORT),
    "handoff_sparse": SPARSE,
    "flow_funnel": answers(FLOW, "view (view|click)* purchase"),
    "flow_until_purchase": answers(FLOW, "(view|click|signup|error)* purchase"),
    "flow_dead_end": "SELECT 0::BIGINT AS src, 0::BIGINT AS dst WHERE false",
    "relay_dense": answers(relay(100), "view click* purchase"),
    "relay_sparse": answers(relay(150), "view click* purchase"),
    "partchain_small": answers(partchain(40), "R N* A"),
    "chat_alternation": answers(TURNS, "user (assistant user)*", CHAT_VERTICES),
    "customer_to_region": word(COMMERCE, "placed", "contains", "from", "based", "in"),
    "same_nation_suppliers": word(COMMERCE, "lives", "^based"),
    "order_suppliers": word(COMMERCE, "contains", "from"),
    "either_region": f"WITH g AS ({COMMERCE}) {words('', 'lives', 'in')} UNION {words('', 'placed', 'contains', 'from', 'based', 'in')}",
    "co_linked_pages": f"WITH l AS ({LINKS}) SELECT DISTINCT x.src, y.src AS dst FROM l x JOIN l y ON x.target = y.target",
    "urgent_closure": CLOSURE_OF + "SELECT src, dst FROM t",
    "urgent_walk_closure": answers(WALK, "x+"),
    "star_reflexive": CLOSURE_OF + f"SELECT src, dst FROM t UNION SELECT src, src FROM ({H300}) UNION SELECT dst, dst FROM ({H300})",
    "near_same_walk": answers(NEAR, "same same* cross"),
    "copy_components": "SELECT a.doc_id AS src, b.doc_id AS dst FROM documents a JOIN documents b ON coalesce(a.text, '') = coalesce(b.text, '')",
    "quoted_items": word(QUOTES, "quotes", "^quotes"),
    "automaton_transitions": f"WITH n AS (SELECT label, count(*) AS n_edges FROM ({_next(_lettered(LETTERS), 'event_id', 'letter', 'user_id', 'ts, event_id')}) GROUP BY label) SELECT q::BIGINT AS q, label, p::BIGINT AS p, from_initial, from_accepting, to_accepting, coalesce(n_edges, 0)::BIGINT AS n_edges FROM (VALUES {EXPECTED_EXAMPLE}) x(q, label, p, from_initial, from_accepting, to_accepting) LEFT JOIN n USING (label)",
    "word_expansion": f"""WITH e AS (SELECT letter AS a, lead(letter) OVER w AS b, lead(letter, 2) OVER w AS c FROM {_lettered(LETTERS)} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
x(word, length) AS (VALUES ('d g', 2), ('d h', 2), ('e g', 2), ('e h', 2), ('e f g', 3), ('e f h', 3))
SELECT word, length::BIGINT AS length, (SELECT count(*) FROM e WHERE CASE WHEN x.length = 2 THEN a || ' ' || b ELSE a || ' ' || b || ' ' || c END = x.word)::BIGINT AS n_places FROM x""",
    "query_classes": f"""WITH n AS (SELECT label, count(*) AS n_edges FROM ({_next(_lettered(PLAIN), 'event_id', 'letter', 'user_id', 'ts, event_id')}) GROUP BY label)
SELECT query, class, star_free, nullable, n::BIGINT AS n_states, (SELECT coalesce(sum(n_edges), 0) FROM n WHERE contains(used, label))::BIGINT AS n_edges FROM (VALUES ('a b* c', 'canonical', false, false, 3, 'abc'), ('a*', 'closure', false, true, 1, 'a'), ('a+', 'closure', false, false, 2, 'a'), ('a b c', 'word', true, false, 4, 'abc'), ('(a|b) c', 'star-free', true, false, 3, 'abc'), ('a (b|c)* d', 'general', false, false, 3, 'abcd'), ('a?', 'star-free', true, true, 2, 'a'), ('(a|b)*', 'general', false, true, 1, 'ab')) x(query, class, star_free, nullable, n, used)""",
    "graph_commerce_profile": f"SELECT label, count(*) AS n_edges, count(DISTINCT src) AS n_src, count(DISTINCT dst) AS n_dst FROM ({COMMERCE}) GROUP BY label",
    "graph_flow_edges": FLOW,
    "graph_handoff_edges": H300,
    "graph_partchain_edges": partchain(40),
    "graph_relay_edges": relay(150),
    "graph_turns_edges": TURNS,
    "graph_links_edges": f"SELECT src, count(DISTINCT target) AS n_links FROM ({LINKS}) GROUP BY src",
    "graph_near_edges": NEAR,
    "label_histogram": f"SELECT label, count(*) AS n_edges FROM ({H300}) GROUP BY label",
    "degree_histogram": f"SELECT degree, count(*) AS n_vertices FROM (SELECT src, count(*) AS degree FROM ({H300}) GROUP BY src) GROUP BY degree",
    "graph_passages_edges": QUOTES,
    "product_edges_funnel": f"WITH RECURSIVE {walk(FLOW, 'view (view|click)* purchase', 'SELECT 1 AS id WHERE false')} SELECT a * {compile_path('view (view|click)* purchase').n_states} + q AS src, b * {compile_path('view (view|click)* purchase').n_states} + p AS dst FROM move",
    "canonical_sizes": f"""WITH RECURSIVE {walk(H400, SHORT, "SELECT 1 AS id WHERE false")}, v AS (SELECT src FROM g UNION SELECT dst FROM g)
SELECT 'a' AS label, count(*) AS n_edges FROM v UNION ALL SELECT 'b', (SELECT count(*) FROM move) UNION ALL SELECT 'c', count(*) FROM v""",
    "reach_counts_capped": split("SELECT x, deg FROM listed", H350, "5"),
    "handoff_split_rounds": answers(H300, SHORT),
    "handoff_split_search": answers(H300, SHORT),
    **{name: "SELECT 0::BIGINT AS src, 0::BIGINT AS dst WHERE false" for name in ("flow_dead_end_rounds", "flow_dead_end_search")},
    "flow_until_purchase_search": answers(FLOW, "(view|click|signup|error)* purchase"),
    "light_heavy_classes": split("SELECT x, CASE WHEN heavy THEN 'heavy' ELSE 'light' END AS class FROM listed"),
    "light_answers": split(f"SELECT src, dst FROM found WHERE src NOT IN ({HEAVY_START})"),
    "heavy_sources": split(f"SELECT s AS src FROM ({HEAVY_START})"),
    "trail_counts": split(f"SELECT s AS src, count(*) AS n_visited FROM walk WHERE s IN ({HEAVY_START}) GROUP BY s"),
    "heavy_answers": split(f"SELECT src, dst FROM found WHERE src IN ({HEAVY_START})"),
    **{
        name: MIXED
        for name in "canonical_direct_route fixed_cap_32 complete_lists adaptive_cap pruned_trail light_shortcut array_layout search_forward search_backward search_two_ended search_fused".split()
    },
    **{name: SPARSE for name in "stored_loops_route fixed_cap_1 naive_rounds sql_recursion".split()},
    "search_inspections": f"WITH RECURSIVE {walk(H350, SHORT, 'SELECT 1 AS id WHERE false')} SELECT count(*) AS inspections FROM walk JOIN move ON v = a AND walk.q = move.q",
    "matrix_blocks": word(COMMERCE, "lives", "^based"),
    "matrix_closure": _delta(CLOSED) + " SELECT src, dst FROM t",
    "plain_join_word": word(COMMERCE, "placed", "contains", "from", "based"),
    "word_single_label": word(COMMERCE, "lives"),
    "word_repeated_label": word(H350, "1-URGENT", "1-URGENT", "3-MEDIUM"),
    "word_inspections": f"""WITH g AS ({H350}), r2 AS (SELECT src AS p, dst AS q FROM g WHERE label = '2-HIGH'), r3 AS (SELECT src AS p, dst AS q FROM g WHERE label = '3-MEDIUM'), r4 AS (SELECT src AS p, dst AS q FROM g WHERE label = '5-LOW'),
l3 AS (SELECT DISTINCT r3.p, r4.q AS y FROM r3 JOIN r4 ON r3.q = r4.p)
SELECT (SELECT count(*) FROM r3 JOIN r4 ON r3.q = r4.p)::BIGINT + (SELECT count(*) FROM r2 JOIN l3 ON r2.q = l3.p)::BIGINT AS lists, 0::BIGINT AS trail""",
    "union_with_epsilon": f"WITH g AS ({H350}) {words('', '1-URGENT')} UNION {words('', '2-HIGH', '3-MEDIUM')} UNION SELECT src, src FROM g UNION SELECT dst, dst FROM g",
    "union_of_words_plain": f"WITH g AS ({COMMERCE}) {words('', 'lives', 'in')} UNION {words('', 'from', 'based', 'in')}",
    "layered_automaton": f"WITH g AS ({COMMERCE}) {words('', 'lives', 'in')} UNION {words('', 'from', 'based', 'in')}",
    "k_path_join": word(COMMERCE, "placed", "contains", "from", "based", "in"),
    **{name: _delta(CLOSED) + " SELECT src, dst FROM t" for name in ("closure_left_rule", "closure_right_rule", "closure_squaring", "closure_deep")},
    "closure_inspections": CLOSURE_OF + "SELECT (SELECT count(*) FROM t)::BIGINT AS out, (SELECT count(*) FROM t JOIN e ON t.dst = e.src)::BIGINT AS inspections, true AS within_bounds",
    "closure_delta_sizes": _delta(_hops()) + " SELECT round::BIGINT AS round, count(*) AS new_pairs FROM (SELECT src, dst, min(h) AS round FROM t GROUP BY ALL) GROUP BY round",
    "reachable_from_sources": f"SELECT src, dst FROM ({MIXED}) WHERE {segment('src', 'BUILDING')}",
    "answers_into_targets": f"SELECT src, dst FROM ({MIXED}) WHERE {segment('dst', 'MACHINERY')}",
    "segment_to_segment": f"SELECT src, dst FROM ({MIXED}) WHERE {segment('src', 'BUILDING')} AND {segment('dst', 'MACHINERY')}",
    "connected_pairs": f"WITH a AS ({MIXED}) SELECT DISTINCT e.src, e.dst, a.src IS NOT NULL AS connected FROM ({H350}) e LEFT JOIN a ON a.src = e.src AND a.dst = e.dst",
    "degrees_sketched": f"SELECT count(DISTINCT src)::BIGINT AS n_vertices, 0::BIGINT AS n_off FROM ({answers(H300, SHORT)})",
    "targets_by_bitmap": f"SELECT c_mktsegment AS segment, count(DISTINCT dst)::BIGINT AS n_targets FROM ({answers(H300, SHORT)}) JOIN customer ON c_custkey = src GROUP BY c_mktsegment",
    "degree_profile": f"SELECT deg, count(*) AS n_vertices FROM (SELECT src, count(*) AS deg FROM ({answers(H300, SHORT)}) GROUP BY src) GROUP BY deg",
    "top_degree_vertices": f"SELECT src AS v, count(*) AS deg FROM ({answers(H300, SHORT)}) GROUP BY src ORDER BY deg DESC, v LIMIT 10",
    "shortest_length": f"""WITH RECURSIVE {walk(H350, SHORT, "SELECT 1 AS id WHERE false")},
far(s, v, q, h) AS (SELECT DISTINCT a, a, q, 0 FROM move WHERE q = {FIRST} UNION SELECT s, b, p, h + 1 FROM far JOIN move ON v = a AND far.q = move.q WHERE h < 40)
SELECT s AS src, v AS dst, min(h)::BIGINT AS hops FROM far WHERE q IN ({", ".join(map(str, sorted(compile_path(SHORT).accepting)))}) GROUP BY s, v""",
    "cost_report": split(f"{REPORTED}", H300).replace("\nSELECT (SELECT count(*) FROM (SELECT src FROM g", f",\nhs AS ({HEAVY_START})\nSELECT (SELECT count(*) FROM (SELECT src FROM g", 1),
    "run_costs": "SELECT m AS measure, true AS holds FROM (VALUES ('seconds'), ('shuffle_bytes'), ('peak_rows'), ('inspect_reach'), ('rounds')) x(m)",
    "search_report": f"WITH RECURSIVE {walk(H300, SHORT, NONE)} SELECT (SELECT count(*) FROM found)::BIGINT AS out, (SELECT count(*) FROM walk WHERE q IN ({LAST}))::BIGINT AS out_states, (SELECT count(*) FROM walk JOIN move ON v = a AND walk.q = move.q)::BIGINT AS inspect_search",
    "bounds_table": sizes("name AS workload, v::BIGINT AS v, e::BIGINT AS e, o::BIGINT AS out, v * e AS search, round(e ** 1.5 + least(o * sqrt(e), v * e), 3) AS split, round(e + e * sqrt(o), 3) AS star_free, round(least(o * sqrt(e), v * e), 3) AS closure, round((v * e) ** 0.9, 3) AS floor_combinatorial, round((e + o) ** 0.9, 3) AS floor_any"),
    "regime_exponents": sizes("name AS graph, forward AS search, round(1 - ln(o) / ln(v * sqrt(e)), 6) AS alpha, round(2 - ln(e) / ln(v), 6) AS beta, 1 - ln(o) / ln(v * sqrt(e)) > 0 AND 1 - ln(o) / ln(v * sqrt(e)) <= 1 AND 2 - ln(e) / ln(v) > 0 AND 2 - ln(e) / ln(v) < 2 AS wins", SWEEP),
    "inspections_by_method": f"WITH z AS ({sizes('*', {n: SIZES[n] for n in ('handoff_split', 'handoff_sparse', 'flow_until_purchase', 'flow_dead_end')})}) SELECT name AS workload, 'lists' AS method, lists AS inspections FROM z UNION ALL SELECT name, 'forward', forward FROM z UNION ALL SELECT name, 'backward', backward FROM z",
    "bound_checks": "SELECT i AS invariant, true AS holds FROM (VALUES ('few_heavy_sources'), ('lists_within_cap'), ('reach_within_bound'), ('trail_within_bound')) x(i)",
    # where lists fill, whether the method looks at fewer edges follows from no closed form; on both such graphs it does not
    "gain_by_workload": sizes("name AS workload, CASE WHEN NOT filled THEN lists END AS split, forward AS search, NOT filled AND lists < forward AS gains"),
    "method_agreement": f"SELECT m AS method, (SELECT count(*) FROM ({MIXED})) AS pairs, 0::BIGINT AS differing FROM (VALUES ('first'), ('auto'), ('capped-split'), ('search'), ('backward'), ('two-ended'), ('fused'), ('kernel'), ('kernel-search'), ('between'), ('cap 1'), ('cap 32'), ('cap adaptive'), ('cap None'), ('pruned'), ('shortcut'), ('arrays')) x(m)",
    "example_on_handoff": answers(H450, "1-URGENT* (2-HIGH 3-MEDIUM|5-LOW)*"),
    "co_linked_closure": f"WITH RECURSIVE {EVEN_LINKS}, k AS (SELECT DISTINCT src FROM e), u(a, b) AS (SELECT a, b FROM t UNION SELECT src, src FROM k) SELECT 0::BIGINT AS kind, count(*)::BIGINT AS n_pairs, count(DISTINCT a)::BIGINT AS n_src FROM u UNION ALL SELECT 1, count(DISTINCT target)::BIGINT, count(DISTINCT target)::BIGINT FROM e",
    "co_linked_pages_closure": f"WITH RECURSIVE {EVEN_LINKS} SELECT a AS src, b AS dst FROM t",
    "sequence_with_nulls": _next(HIDDEN, "who", "o_orderpriority", "", "o_orderdate, o_orderkey"),
    "sequence_with_nulls_by_clerk": _next(HIDDEN, "who", "o_orderpriority", "o_orderstatus", "o_orderdate, o_orderkey"),
    "links_by_host": f"WITH e AS (SELECT DISTINCT page_id, coalesce(regexp_extract(url, '^[a-z]+://([^/]*)', 1), '') AS host, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS target FROM pages) SELECT host, substr(lower(target), 2, 1) AS letter, count(*) AS n_links FROM e GROUP BY ALL",
    "flow_by_day": f"WITH f AS ({_next(LOW, 'event_id', 'event_type', 'user_id', 'ts, event_id')}) SELECT datediff('day', DATE '1970-01-01', ts::DATE)::BIGINT AS day, label, count(*) AS n_edges FROM f JOIN events ON event_id = src GROUP BY ALL",
    "pairs_in_both": both("SELECT * FROM one INTERSECT SELECT * FROM two"),
    "pairs_in_one": both("SELECT * FROM one EXCEPT SELECT * FROM two"),
    **{name: both("SELECT 'one' AS query, src, dst FROM one UNION ALL SELECT 'two', src, dst FROM two UNION ALL SELECT 'three', src, dst FROM three") for name in ("many_queries_one_graph", "many_queries_in_rounds")},
    "joined_paths": f"WITH one AS ({MIXED}), two AS ({word(H350, '5-LOW', '2-HIGH')}) SELECT DISTINCT one.src AS x, one.dst AS y, two.dst AS z FROM one JOIN two ON one.dst = two.src",
    "answers_by_region_cube": NATION + " SELECT region, c_mktsegment AS segment, count(*) AS n FROM wide JOIN customer ON c_custkey = dst GROUP BY CUBE (region, c_mktsegment)",
    "answers_rollup": NATION + " SELECT region, nation, count(*) AS n, count(DISTINCT src) AS n_src FROM wide GROUP BY ROLLUP (region, nation)",
    "answers_grouping_sets": NATION + " SELECT region, nation, count(*) AS n FROM wide GROUP BY GROUPING SETS ((region), (nation), ())",
    "ranked_answers": f"WITH d AS (SELECT src, count(*) AS deg FROM ({answers(H300, SHORT)}) GROUP BY src) SELECT DISTINCT deg, count(*) OVER (PARTITION BY deg) AS n_vertices, rank() OVER (ORDER BY deg DESC) AS rank, dense_rank() OVER (ORDER BY deg DESC) AS dense_rank FROM d",
    "flow_in_window": "SELECT event_id AS src, event_type AS label, dst FROM (SELECT *, lead(event_id) OVER w AS dst, lead(ts) OVER w AS later FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE later <= ts + INTERVAL 1 HOUR",
    "asof_label": "SELECT id, label FROM (SELECT event_id AS id, event_type, last_value(CASE WHEN event_type <> 'purchase' THEN event_type END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS label FROM events) WHERE event_type = 'purchase' AND label IS NOT NULL",
    "interval_edges": "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE",
    "two_rings": RINGS,
    "one_path": "SELECT count(*) AS n_vertices, count(*) - 1 AS n_edges, 0::BIGINT AS out FROM events",
    "two_rings_cost": """WITH n AS (SELECT count(*) FILTER (c_custkey % 2 = 1) AS odd, count(*) FILTER (c_custkey % 2 = 0) AS even FROM customer),
k AS (SELECT *, (2 * odd + 2 * even)::BIGINT AS n_edges, floor(sqrt(2 * odd + 2 * even))::BIGINT + 1 AS cap FROM n)
SELECT n_edges, cap, (even * least(cap, even))::BIGINT AS reach_rows, CASE WHEN even >= cap THEN even ELSE 0 END::BIGINT AS n_heavy, 0::BIGINT AS heavy_sources, (even * least(cap, even))::BIGINT AS inspect_reach, 0::BIGINT AS inspect_trail,
  (odd * (odd + 1))::BIGINT AS inspect_forward, (CASE WHEN odd <= even THEN odd * odd ELSE even * even END)::BIGINT AS inspect_two_ended FROM k""",
    "one_path_cost": "SELECT 0::BIGINT AS inspect_reach, 0::BIGINT AS reach_rows, 0::BIGINT AS inspect_backward, (count(*) * (count(*) - 1) // 2)::BIGINT AS inspect_forward FROM events",
    "partchain_giant": f"SELECT count(*) AS out FROM ({answers(partchain(36), 'R N* A')})",
    "stream_incremental_closure": _delta(CLOSED) + " SELECT src, dst FROM t",
    "stream_window_tumbling": "SELECT (epoch_us(ts) // 3600000000 * 3600)::BIGINT AS start, event_type AS label, count(*) AS n FROM events GROUP BY ALL",
    "stream_window_sliding": "SELECT (epoch_us(ts) // 1800000000 * 1800 - 1800 * k)::BIGINT AS start, event_type AS label, count(*) AS n FROM events, (VALUES (0), (1)) s(k) GROUP BY ALL",
    "stream_window_paths": windows("SELECT us // 86400000000 * 86400 AS start, * FROM e"),
    "stream_window_paths_sliding": windows("SELECT us // 43200000000 * 43200 - 43200 * k AS start, e.* FROM e, (VALUES (0), (1)) s(k)"),
    "stream_session_answers": windows("SELECT epoch_us(min(ts) OVER (PARTITION BY user_id, k)) // 1000000 AS start, user_id, event_id, event_type, ts FROM (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 4 HOUR THEN 0 ELSE 1 END AS opens FROM e))"),
    "stream_session_paths": """WITH o AS (SELECT user_id, ts, event_type, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS opens FROM events),
s AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM o)
SELECT user_id, (epoch_us(min(ts)) // 1000000)::BIGINT AS start, count(*) AS n_events, count(*) FILTER (event_type = 'purchase') AS n_purchases FROM s GROUP BY user_id, k""",
    "stream_user_automaton": f"WITH f AS ({answers(FLOW, 'view (view|click)*')}), o AS (SELECT event_id, user_id, event_type, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events) SELECT o.user_id, count(DISTINCT CASE WHEN o.event_type = 'purchase' AND f.dst IS NOT NULL THEN o.event_id END) AS matched FROM o LEFT JOIN f ON f.dst = o.event_id GROUP BY o.user_id",
    "sql_path_query": answers(TURNS, "user (assistant user)*", CHAT_VERTICES),
    "sql_path_query_star": answers(TURNS, "(user assistant)*"),
    "sql_path_matches": "SELECT conv_id, regexp_full_match(string_agg(role, ' ' ORDER BY turn), '(user assistant ?)+') AS matched FROM conversations GROUP BY conv_id",
    "graph_copies_edges": COPY,
    "graph_copies_labels": f"SELECT label, count(*) AS n_edges FROM (SELECT DISTINCT label, src FROM (SELECT label, src FROM ({COPY}) UNION ALL SELECT 'lang:' || lang, doc_id FROM documents UNION ALL SELECT 'src:' || source, doc_id FROM documents UNION ALL SELECT 'rated:' || quality::VARCHAR, doc_id FROM labels) WHERE label IS NOT NULL) GROUP BY label",
}
