"""Graphs and queries over the given tables, and the queries() entries made from them."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathq.functions import bounds, sqlapi
from pathq.functions.metrics import RunReport
from pathq.operators import kernels, matrix
from pathq.operators.capped_split import evaluate_capped_split, heavy_sources, heavy_walk, light_answers
from pathq.operators.closure import class_pairs, closure_in_tasks, delta_sizes, transitive_closure
from pathq.operators.product import Canonical, default_cap, direct, product_edges, stored_loops
from pathq.operators.reach import capped_reach, split
from pathq.operators.reachable import answers_into, capped_degrees, decide, degrees, reachable, shortest_length, sketched
from pathq.operators.search import arrivals, forward_looks, fused_search, product_search, recursive_sql
from pathq.operators.starfree import evaluate_layered, evaluate_star_free, path_join, plain_join, relations
from pathq.plans.automaton import compile_path, minimise, to_dfa, to_nfa
from pathq.plans.classify import classify, expand_words
from pathq.plans.expr import as_expr, reverse
from pathq.plans.planner import INNER, METHODS, canonical_of, evaluate, evaluate_many, evaluate_with_report, join_paths, report_only
from pathq.sources.builders import from_foreign_keys, from_links, from_sequence, nearest_by_cosine, occurrences, typed
from pathq.sources.graph import PathGraph
from pathq.store import Store
from pathq.streaming import incremental

Query = Callable[[SparkSession, str], DataFrame]

# --- graphs --------------------------------------------------------------------------------------------------------


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def commerce(spark, d) -> PathGraph:
    c, o, li, s, n = (_t(spark, d, x) for x in ("customer", "orders", "lineitem", "supplier", "nation"))
    return from_foreign_keys(
        [
            (o, typed("customer", "o_custkey"), typed("order", "o_orderkey"), "placed"),
            (li, typed("order", "l_orderkey"), typed("part", "l_partkey"), "contains"),
            (li, typed("part", "l_partkey"), typed("supplier", "l_suppkey"), "from"),
            (c, typed("customer", "c_custkey"), typed("nation", "c_nationkey"), "lives"),
            (s, typed("supplier", "s_suppkey"), typed("nation", "s_nationkey"), "based"),
            (n, typed("nation", "n_nationkey"), typed("region", "n_regionkey"), "in"),
        ]
    )


def flow(spark, d) -> PathGraph:
    e = _t(spark, d, "events")
    g = from_sequence(e, ["user_id"], ["ts", "event_id"], "event_id", "event_type")
    return PathGraph(g.edges, e.select(F.col("event_id").alias("id")))


def flow_component(spark, d) -> DataFrame:
    return _t(spark, d, "events").select(F.col("event_id").alias("id"), F.col("user_id").alias("part"))


def relay(spark, d, above: float) -> PathGraph:
    return from_sequence(_t(spark, d, "events").filter(F.col("value") > above), [], ["ts", "event_id"], "user_id", "event_type")


def handoff(spark, d, above: int) -> PathGraph:
    return from_sequence(_t(spark, d, "orders").filter(F.col("o_totalprice") > above), [], ["o_orderdate", "o_orderkey"], "o_custkey", "o_orderpriority")


def urgent_walk(spark, d) -> PathGraph:
    o = _t(spark, d, "orders").filter((F.col("o_totalprice") > 450_000) & (F.col("o_orderpriority") == "1-URGENT"))
    return from_sequence(o, [], ["o_orderdate", "o_orderkey"], "o_custkey", F.lit("x"))


def partchain(spark, d, least: int) -> PathGraph:
    li = _t(spark, d, "lineitem").filter(F.col("l_quantity") >= least)
    return from_sequence(li, ["l_orderkey"], ["l_linenumber", "l_partkey", "l_suppkey", "l_shipdate"], "l_partkey", "l_returnflag")


def turns(spark, d) -> PathGraph:
    c = _t(spark, d, "conversations")
    vertex = F.col("conv_id") * 1000 + F.col("turn")
    g = from_sequence(c, ["conv_id"], ["turn"], vertex, "role")
    return PathGraph(g.edges, c.select(vertex.alias("id")))


def links(spark, d) -> PathGraph:
    return from_links(_t(spark, d, "pages"))


def near(spark, d, k: int = 3) -> PathGraph:
    v = _t(spark, d, "embeddings")
    kind = v.select("vec_id", "label")
    pairs = nearest_by_cosine(v, k).join(kind.withColumnRenamed("vec_id", "query_id").withColumnRenamed("label", "l1"), "query_id").join(kind.withColumnRenamed("label", "l2"), "vec_id")
    return PathGraph.from_edges(pairs, "query_id", F.when(F.col("l1") == F.col("l2"), "same").otherwise("cross"), "vec_id")


def copies(spark, d) -> PathGraph:
    """copy: to the first document with the same text; lang:, src: and rated: to vertices of attributes, with negative ids."""
    docs = _t(spark, d, "documents").select("doc_id", "lang", "source", F.md5(F.coalesce("text", F.lit(""))).alias("h"))
    first = docs.groupBy("h").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    copy = docs.join(first, "h").filter("doc_id <> first").select(F.col("doc_id").alias("src"), F.lit("copy").alias("label"), F.col("first").alias("dst"))
    attribute = lambda df, key, prefix: df.select(F.col("doc_id").alias("src"), F.concat(F.lit(prefix), F.col(key)).alias("label"), (-F.crc32(F.concat(F.lit(prefix), F.col(key))) - 1).alias("dst"))
    rated = _t(spark, d, "labels").select("doc_id", F.col("quality").cast("string").alias("quality"))
    edges = copy.unionByName(attribute(docs, "lang", "lang:")).unionByName(attribute(docs, "source", "src:")).unionByName(attribute(rated, "quality", "rated:"))
    return PathGraph(PathGraph.from_edges(edges).edges, docs.select(F.col("doc_id").alias("id")))


def passages(spark, d) -> PathGraph:
    met = occurrences(_t(spark, d, "documents"), _t(spark, d, "benchmark"))
    return PathGraph.from_edges(met, F.col("doc_id") * 2, F.lit("quotes"), F.col("item_id") * 2 + 1)


def one_path(spark, d) -> PathGraph:
    return from_sequence(_t(spark, d, "events"), [], ["event_id"], "event_id", F.lit("b"))


def two_rings(spark, d) -> PathGraph:
    c = _t(spark, d, "customer")
    out = None
    for odd, labels in ((1, ("a", "b")), (0, ("b", "c"))):
        ring = c.filter(F.col("c_custkey") % 2 == odd)
        ends = ring.agg(F.max("c_custkey").alias("src"), F.min("c_custkey").alias("dst"))
        steps = from_sequence(ring, [], ["c_custkey"], "c_custkey", F.lit("x")).edges.select("src", "dst").unionByName(ends)
        both = steps.withColumn("label", F.explode(F.array(*map(F.lit, labels))))
        out = both if out is None else out.unionByName(both)
    return PathGraph.from_edges(out)


SHORT = "1-URGENT 3-MEDIUM* 5-LOW"
EVENTS = "(view|click|signup|purchase|error)*"

# name: (graph, expression, method, options)
WORKLOADS: dict[str, tuple[Callable, str, str]] = {
    "handoff_split": (partial(handoff, above=300_000), SHORT, "auto"),
    "handoff_sparse": (partial(handoff, above=400_000), SHORT, "auto"),
    "flow_funnel": (flow, "view (view|click)* purchase", "component"),
    "flow_until_purchase": (flow, "(view|click|signup|error)* purchase", "component"),
    "flow_dead_end": (flow, f"{EVENTS} refund", "auto"),
    "relay_dense": (partial(relay, above=100), "view click* purchase", "auto"),
    "relay_sparse": (partial(relay, above=150), "view click* purchase", "auto"),
    "partchain_small": (partial(partchain, least=40), "R N* A", "auto"),
    "chat_alternation": (turns, "user (assistant user)*", "auto"),
    "customer_to_region": (commerce, "placed contains from based in", "auto"),
    "same_nation_suppliers": (commerce, "lives ^based", "auto"),
    "order_suppliers": (commerce, "contains from", "auto"),
    "either_region": (commerce, "(lives|placed contains from based) in", "auto"),
    "co_linked_pages": (links, "links ^links", "auto"),
    "urgent_closure": (partial(handoff, above=300_000), "1-URGENT+", "auto"),
    "urgent_walk_closure": (urgent_walk, "x+", "auto"),
    "star_reflexive": (partial(handoff, above=300_000), "1-URGENT*", "auto"),
    "near_same_walk": (near, "same same* cross", "auto"),
    "copy_components": (copies, "(copy|^copy)*", "auto"),
    "quoted_items": (passages, "quotes ^quotes", "auto"),
}


def run_workload(name: str, spark: SparkSession, d: str) -> DataFrame:
    graph, expr, method = WORKLOADS[name]
    options = {"component": flow_component(spark, d)} if method == "component" else {}
    return evaluate(graph(spark, d), expr, method, later=True, **options)


# --- small things shared by entries --------------------------------------------------------------------------------


def _rows(spark: SparkSession, rows: list, schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def _prepared(spark, d, above: int = 350_000, expr: str = SHORT) -> tuple[PathGraph, Canonical, Store]:
    """A hand-off graph and its canonical form, written once for an entry."""
    store = Store(spark, "entry")
    g = PathGraph(store.table(handoff(spark, d, above).edges, "edges"))
    return g, canonical_of(g, expr, store)[0], store


def _phases(spark, d):
    """Lists and split under the default cap of a graph where both classes occur."""
    g, canon, store = _prepared(spark, d, 325_000)
    cap = default_cap(canon.n_edges())
    reach, _ = capped_reach(canon, cap, store)
    light, heavy, _ = split(store.table(reach, "lists"), cap, store)
    return canon, light, heavy, store


EXAMPLE = "d*(e f|g)*"
STAR_FREE = "(d|e f?) (g|h)"


#: Event types that play the letters of the expressions below.
LETTERS = {"view": "d", "click": "e", "signup": "f", "purchase": "g", "error": "h"}
PLAIN = {"view": "a", "click": "b", "purchase": "c", "error": "d"}


def _lettered(spark, d, letters: dict[str, str]) -> DataFrame:
    """Events that have a letter, with it."""
    named = F.create_map(*[F.lit(x) for pair in letters.items() for x in pair])
    return _t(spark, d, "events").withColumn("letter", F.element_at(named, F.col("event_type"))).filter("letter is not null")


def _edges_per_letter(spark, d, letters: dict[str, str]) -> DataFrame:
    return from_sequence(_lettered(spark, d, letters), ["user_id"], ["ts", "event_id"], "event_id", "letter").label_histogram()


def automaton_transitions(spark, d):
    """The minimal automaton of the worked expression, and the edges of the flow of events that each transition matches."""
    a = minimise(to_dfa(to_nfa(EXAMPLE)))
    rows = [(q, s.label, p, q in a.initial, q in a.accepting, p in a.accepting) for q, s, p in a.transitions]
    told = _rows(spark, sorted(rows), "q long, label string, p long, from_initial boolean, from_accepting boolean, to_accepting boolean")
    return told.join(_edges_per_letter(spark, d, LETTERS), "label", "left").fillna(0, ["n_edges"])


def word_expansion(spark, d):
    """The words of a star-free expression, and how often consecutive events of a user spell each."""
    words, empty = expand_words(STAR_FREE)
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    ahead = [F.lead("letter", i).over(w) if i else F.col("letter") for i in range(max(map(len, words)))]
    read = _lettered(spark, d, LETTERS).select(F.array(*ahead).alias("ahead"))
    lengths = sorted({len(x) for x in words})
    spelled = read.select(F.explode(F.array(*[F.when(F.element_at("ahead", n).isNotNull(), F.array_join(F.slice("ahead", 1, n), " ")) for n in lengths])).alias("word"))
    told = _rows(spark, [(" ".join(s.label for s in x), len(x)) for x in words], "word string, length long")
    return told.join(spelled.groupBy("word").agg(F.count(F.lit(1)).alias("n_places")), "word", "left").fillna(0, ["n_places"])


def query_classes(spark, d):
    """Classes of expressions, and the edges of the flow of events whose labels each can use."""
    rows = []
    for q in ("a b* c", "a*", "a+", "a b c", "(a|b) c", "a (b|c)* d", "a?", "(a|b)*"):
        c = classify(q)
        rows.append((q, c.name, c.star_free, c.nullable, compile_path(q).n_states, sorted(c.labels)))
    told = _rows(spark, rows, "query string, class string, star_free boolean, nullable boolean, n_states long, labels array<string>")
    used = told.select("query", F.explode("labels").alias("label")).join(_edges_per_letter(spark, d, PLAIN), "label")
    return told.drop("labels").join(used.groupBy("query").agg(F.sum("n_edges").alias("n_edges")), "query", "left").fillna(0, ["n_edges"])


def edges_of(graph: Callable, spark, d):
    return graph(spark, d).edges.select("src", "label", "dst")


def commerce_profile(spark, d):
    g = commerce(spark, d)
    return g.edges.groupBy("label").agg(F.count(F.lit(1)).alias("n_edges"), F.countDistinct("src").alias("n_src"), F.countDistinct("dst").alias("n_dst"))


def label_histogram(spark, d):
    return handoff(spark, d, 300_000).label_histogram()


def degree_histogram(spark, d):
    return handoff(spark, d, 300_000).degree_histogram()


def product_edges_funnel(spark, d):
    g = flow(spark, d).restrict_labels({"view", "click", "purchase"})
    return product_edges(g, compile_path("view (view|click)* purchase"))


def canonical_sizes(spark, d):
    g = handoff(spark, d, 400_000)
    a = compile_path(SHORT)
    loops = stored_loops(g.restrict_labels(classify(SHORT).labels), a)
    return loops.groupBy("label").agg(F.count(F.lit(1)).alias("n_edges"))


def reach_counts_capped(spark, d):
    g, canon, store = _prepared(spark, d)
    return store.finish(capped_degrees(canon, 5, store))[0]


def light_heavy_classes(spark, d):
    canon, light, heavy, store = _phases(spark, d)
    a = light.select("x").distinct().withColumn("class", F.lit("light"))
    return store.finish(a.unionByName(heavy.withColumn("class", F.lit("heavy"))))[0]


def light_answers_entry(spark, d):
    canon, light, heavy, store = _phases(spark, d)
    return store.finish(light_answers(canon.starts, light).distinct())[0]


def heavy_sources_entry(spark, d):
    canon, light, heavy, store = _phases(spark, d)
    return store.finish(heavy_sources(canon.starts, heavy).select(F.col("s").alias("src")))[0]


def trail_counts(spark, d):
    canon, light, heavy, store = _phases(spark, d)
    walked, _, _ = heavy_walk(canon.starts, canon.middle, heavy, store)
    return store.finish(walked.groupBy(F.col("s").alias("src")).agg(F.count(F.lit(1)).alias("n_visited")))[0]


def heavy_answers_entry(spark, d):
    canon, light, heavy, store = _phases(spark, d)
    walked, _, _ = heavy_walk(canon.starts, canon.middle, heavy, store)
    return store.finish(arrivals(walked, canon.ends).distinct())[0]


def variant(spark, d, above: int = 350_000, **options):
    g, canon, store = _prepared(spark, d, above)
    return store.finish(evaluate_capped_split(canon, store, **options)[0])[0]


def handoff_split_rounds(spark, d):
    """The whole method in rounds, which are made inside tasks while the edges fit one, on the graph where both classes occur under the default cap."""
    return evaluate(handoff(spark, d, 300_000), SHORT, "capped-split", later=True)


def handoff_split_search(spark, d):
    """Its baseline on the same graph."""
    return evaluate(handoff(spark, d, 300_000), SHORT, "search")


def flow_dead_end_rounds(spark, d, method: str = "capped-split"):
    """No list ever begins, so the method ends after its first look, however long the chains."""
    return evaluate(flow(spark, d), WORKLOADS["flow_dead_end"][1], method)


def flow_searched(spark, d, name: str):
    """The search baseline of a workload on chains of events, one task per user."""
    graph, expr, _ = WORKLOADS[name]
    return evaluate(graph(spark, d), expr, "component-search", component=flow_component(spark, d))


def canonical_direct_route(spark, d):
    store = Store(spark, "direct")
    return store.finish(evaluate_capped_split(direct(handoff(spark, d, 350_000), "1-URGENT", "3-MEDIUM", "5-LOW"), store)[0])[0]


def stored_loops_route(spark, d):
    g = handoff(spark, d, 400_000).restrict_labels(classify(SHORT).labels)
    a, store = compile_path(SHORT), Store(spark, "loops")
    canon = direct(PathGraph(store.table(stored_loops(g, a), "loops")))
    found, _ = evaluate_capped_split(canon, store)
    n = a.n_states
    return store.finish(found.select(F.floor(F.col("src") / n).cast("long").alias("src"), F.floor(F.col("dst") / n).cast("long").alias("dst")).distinct())[0]


def searched(spark, d, direction: str, naive: bool = False, above: int = 350_000):
    g, canon, store = _prepared(spark, d, above)
    return store.finish(product_search(canon, store, direction, naive)[0])[0]


def search_fused(spark, d):
    g, canon, store = _prepared(spark, d)
    return store.finish(fused_search(g.restrict_labels(classify(SHORT).labels), compile_path(SHORT), store)[0])[0]


def search_inspections(spark, d):
    """Edges looked at by the forward search: each visited (start, vertex) pair looks at its out-edges once."""
    g, canon, store = _prepared(spark, d)
    return _rows(spark, [(product_search(canon, store)[1]["inspect_search"],)], "inspections long")


def matrix_blocks(spark, d):
    store = Store(spark, "matrix")
    return store.finish(matrix.matrix_word(relations(commerce(spark, d), tuple(classify("lives ^based").word)), store))[0]


def matrix_closure_entry(spark, d):
    store = Store(spark, "matrix")
    return store.finish(matrix.matrix_closure(_urgent(spark, d, 350_000).distinct(), store))[0]


def plain_join_word(spark, d):
    g = commerce(spark, d)
    return plain_join(relations(g, tuple(classify("placed contains from based").word)))


def sql_recursion(spark, d):
    """Recursive SQL as a baseline, deepened until a level adds no pair."""
    g, canon, store = _prepared(spark, d, 400_000)
    return store.finish(recursive_sql(canon, store)[0])[0]


def star_free(spark, d, expr: str, plain: bool = False):
    return evaluate(commerce(spark, d), expr, "plain-words" if plain else "star-free")


def word_repeated_label(spark, d):
    return evaluate(handoff(spark, d, 350_000), "1-URGENT 1-URGENT 3-MEDIUM", "star-free")


def word_inspections(spark, d):
    """Rows that the joins of one word's lists make: complete lists, so that they do not depend on what a cap keeps."""
    parts = relations(handoff(spark, d, 350_000), tuple(classify("1-URGENT 2-HIGH 3-MEDIUM 5-LOW").word))
    told = path_join(parts, Store(spark, "words"), 1 << 30)[1]
    return _rows(spark, [(told["inspect_reach"], told["inspect_trail"])], "lists long, trail long")


def union_with_epsilon(spark, d):
    return evaluate(handoff(spark, d, 350_000), "(1-URGENT|2-HIGH 3-MEDIUM)?", "star-free")


def layered_automaton(spark, d):
    return evaluate(commerce(spark, d), "(lives|from based) in", "layered")


def k_path_join(spark, d):
    store = Store(spark, "k-path")
    return store.finish(path_join(relations(commerce(spark, d), tuple(classify("placed contains from based in").word)), store, 4)[0])[0]


def _urgent(spark, d, above: int) -> DataFrame:
    return handoff(spark, d, above).edges.filter(F.col("label") == "1-URGENT").select("src", "dst")


def closed(spark, d, rule: str, above: int = 350_000):
    store = Store(spark, "closure")
    return store.finish(transitive_closure(_urgent(spark, d, above), store, rule, patience=4)[0])[0]


def closure_inspections(spark, d):
    """Edge looks of the delta rounds on the graph of ``urgent_closure``, and whether its two bounds hold."""
    e = _urgent(spark, d, 300_000).distinct()
    store = Store(spark, "closure")
    e = store.table(e, "urgent")
    told = closure_in_tasks(e, store, only="counters")
    found, log = told or transitive_closure(e, store)
    out = found.count() if found is not None else log.seeds + sum(log.new_rows)
    n, v = e.count(), e.select(F.explode(F.array("src", "dst")).alias("id")).distinct().count()
    store.close()
    return _rows(spark, [(out, log.inspected, log.inspected <= bounds.bound_closure(v, n, out))], "out long, inspections long, within_bounds boolean")


def closure_delta_sizes(spark, d):
    return delta_sizes(_urgent(spark, d, 350_000), Store(spark, "closure"))


def reachable_from_sources(spark, d):
    """Answers from all customers of one market segment."""
    g, canon, store = _prepared(spark, d)
    some = _t(spark, d, "customer").filter(F.col("c_mktsegment") == "BUILDING").select(F.col("c_custkey").alias("id"))
    return store.finish(reachable(canon, some, store))[0]


def answers_into_targets(spark, d):
    """Answers into all customers of one market segment."""
    g, canon, store = _prepared(spark, d)
    some = _t(spark, d, "customer").filter(F.col("c_mktsegment") == "MACHINERY").select(F.col("c_custkey").alias("id"))
    return store.finish(answers_into(canon, some, store))[0]


def connected_pairs(spark, d):
    """For every two customers whose orders follow each other, under whatever label, whether the later one is an answer of the earlier."""
    g, canon, store = _prepared(spark, d)
    return store.finish(decide(canon, g.edges.select("src", "dst").distinct(), store))[0]


def segment_to_segment(spark, d):
    """Answers between two market segments: sources and targets given."""
    c = _t(spark, d, "customer")
    some = lambda x: c.filter(F.col("c_mktsegment") == x).select(F.col("c_custkey").alias("id"))
    return evaluate(handoff(spark, d, 350_000), SHORT, sources=some("BUILDING"), targets=some("MACHINERY"))


def degrees_sketched(spark, d):
    """Degrees from distinct-count sketches over answers by every path end: how many there are, and how many are off by more than a fifth."""
    found = evaluate(handoff(spark, d, 300_000), SHORT, later=True, kernel_limit=1)  # searched where they are counted, at any size
    twice = found.withColumn("end", F.explode(F.array(F.lit(1), F.lit(2))))
    # answers are found once, when both degrees read them
    both = sketched(twice, F.count_if(F.col("end") == 1).alias("deg"))
    return both.agg(F.count(F.lit(1)).alias("n_vertices"), F.count_if(F.abs(F.col("about") - F.col("deg")) > F.col("deg") * 0.2 + 1).alias("n_off"))


def targets_by_bitmap(spark, d):
    """Distinct answer ends per market segment of the start, counted by bitmaps that are united."""
    c = _t(spark, d, "customer").select(F.col("c_custkey").alias("src"), F.col("c_mktsegment").alias("segment"))
    found = evaluate(handoff(spark, d, 300_000), SHORT).join(c, "src")
    bits = found.groupBy("segment", F.bitmap_bucket_number("dst").alias("page")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("dst")).alias("bits"))
    return bits.groupBy("segment").agg(F.sum(F.bitmap_count("bits")).alias("n_targets"))


def degree_profile(spark, d):
    g = handoff(spark, d, 300_000)
    return degrees(evaluate(g, SHORT, later=True)).groupBy("deg").agg(F.count(F.lit(1)).alias("n_vertices"))


def top_degree_vertices(spark, d):
    g = handoff(spark, d, 300_000)
    return degrees(evaluate(g, SHORT, later=True)).orderBy(F.desc("deg"), "v").limit(10)


def shortest_length_entry(spark, d):
    g, canon, store = _prepared(spark, d)
    return store.finish(shortest_length(canon, store))[0]


def _report(spark, d) -> RunReport:
    """The whole method in rounds, on the graph where light and heavy vertices occur under the default cap."""
    return report_only(handoff(spark, d, 300_000), SHORT, "capped-split")


REPORTED = ("n_vertices", "n_edges", "n_labels", "out", "product_vertices", "product_edges", "canonical_edges", "cap", "reach_rows", "n_light", "n_heavy", "n_absent", "heavy_sources", "light_rows", "heavy_rows", "trail_rows", "inspect_trail")


def cost_report(spark, d):
    """What the data alone determine of the report; looks at lists, time and shuffles depend on the run."""
    r = _report(spark, d)
    return _rows(spark, [tuple(getattr(r, c) for c in REPORTED)], ", ".join(f"{c} long" for c in REPORTED))


def run_costs(spark, d):
    """That time, shuffled bytes, rows of the largest task and looks at lists are told, and within what has to hold."""
    r = _report(spark, d)
    told = [("seconds", r.seconds > 0), ("shuffle_bytes", r.shuffle_bytes > 0), ("peak_rows", 0 < r.peak_rows <= r.canonical_edges * r.cap), ("inspect_reach", 0 < r.inspect_reach <= r.canonical_edges * r.cap), ("rounds", 0 < r.rounds <= 2 * r.product_vertices)]
    return _rows(spark, told, "measure string, holds boolean")


def search_report(spark, d):
    """The search's own report on the same graph: answers with states, visited edges."""
    r = evaluate_with_report(handoff(spark, d, 300_000), SHORT, "search")[1]
    return _rows(spark, [(r.out, r.out_states, r.inspect_search)], "out long, out_states long, inspect_search long")


_BOUNDED = ("handoff_split", "handoff_sparse", "flow_funnel", "flow_until_purchase", "flow_dead_end", "relay_dense", "relay_sparse", "partchain_small")
_SWEEP: dict[str, tuple[Callable, str]] = {
    "handoff 300k": (partial(handoff, above=300_000), SHORT),
    "handoff 350k": (partial(handoff, above=350_000), SHORT),
    "handoff 400k": (partial(handoff, above=400_000), SHORT),
    "partchain 36": (partial(partchain, least=36), "R N* A"),
    "partchain 40": (partial(partchain, least=40), "R N* A"),
    "relay 100": (partial(relay, above=100), "view click* purchase"),
    "relay 150": (partial(relay, above=150), "view click* purchase"),
}


def _method_of(name: str, spark, d, search: bool = False) -> tuple[str, dict]:
    """How a workload is evaluated in tasks: by its known key, or whole."""
    if name.startswith("flow"):
        return ("component-search" if search else "component"), {"component": flow_component(spark, d)}
    return ("kernel-search" if search else "kernel"), {}


def _sized(spark, d):
    for name in _BOUNDED:
        graph, expr, _ = WORKLOADS[name]
        method, options = _method_of(name, spark, d, search=True)
        r = report_only(graph(spark, d), expr, method, **options)
        yield name, r.n_vertices, r.n_edges, r.out


def bounds_table(spark, d):
    """Closed forms on measured sizes; the floors are what conditional lower bounds leave, at an exponent of 0.9."""
    rows = [
        (n, v, e, o, bounds.bound_search(v, e), round(bounds.bound_split(v, e, o), 3), round(bounds.bound_star_free(e, o), 3), round(bounds.bound_closure(v, e, o), 3), round(bounds.floor_combinatorial(v, e), 3), round(bounds.floor_any(e, o), 3))
        for n, v, e, o in _sized(spark, d)
    ]
    return _rows(spark, rows, "workload string, v long, e long, out long, search double, split double, star_free double, closure double, floor_combinatorial double, floor_any double")


def regime_exponents(spark, d):
    """Exponents of the sizes over a sweep of densities, and whether they lie where the method is strictly cheaper."""
    rows = []
    for name, (graph, expr) in _SWEEP.items():
        r = report_only(graph(spark, d), expr, "kernel-search")
        alpha, beta = bounds.regime(r.n_vertices, r.n_edges, r.out)
        rows.append((name, r.inspect_search, round(alpha, 6), round(beta, 6), bounds.wins(r.n_vertices, r.n_edges, r.out)))
    return _rows(spark, rows, "graph string, search long, alpha double, beta double, wins boolean")


COUNTED = ("handoff_split", "handoff_sparse", "flow_until_purchase", "flow_dead_end")


def inspections_by_method(spark, d):
    """Edges looked at by complete lists, forward and backward search, all counted while they run."""
    rows = []
    for name in COUNTED:
        graph, expr, _ = WORKLOADS[name]
        g = graph(spark, d)
        for kind in ("lists", "forward", "backward"):
            method, options = _method_of(name, spark, d, kind != "lists")
            if kind == "backward":
                g, expr = g.reversed(), reverse(as_expr(expr))
            if method == "component":
                r = evaluate_with_report(g, expr, method, cap=None, **options)[1]
            else:
                r = report_only(g, expr, method, **options, **({"cap": None} if kind == "lists" else {}))
            rows.append((name, kind, r.inspect_reach if kind == "lists" else r.inspect_search))
    return _rows(spark, rows, "workload string, method string, inspections long")


def bound_checks(spark, d):
    """Inequalities that every run keeps, on one with heavy sources."""
    r = _report(spark, d)
    assert r.heavy_sources or r.n_heavy == 0
    return _rows(spark, sorted(r.invariants().items()), "invariant string, holds boolean")


def gain_by_workload(spark, d):
    """The method under its default cap against the forward search, both counted while they run.

    ``split`` is left out where lists fill, as the looks then depend on which entries a cap keeps.
    """
    rows = []
    for name in _BOUNDED:
        graph, expr, _ = WORKLOADS[name]
        g = graph(spark, d)
        method, options = _method_of(name, spark, d)
        if method == "kernel":  # looks only: the answers are not needed
            store = Store(spark, "gain")
            told = kernels.in_tasks(canonical_of(g, expr, store)[0], store, only="counters")[1]
            own = RunReport(inspect_reach=told["inspect_reach"], inspect_trail=told["inspect_trail"], n_heavy=told["n_heavy"])
            store.close()
        else:
            own = evaluate_with_report(g, expr, method, **options)[1]
        method, options = _method_of(name, spark, d, search=True)
        base = report_only(g, expr, method, **options)
        rows.append((name, None if own.n_heavy else own.inspected, base.inspect_search, own.inspected < base.inspect_search))
    return _rows(spark, rows, "workload string, split long, search long, gains boolean")


def method_agreement(spark, d):
    """Per method, its pairs and those on which it differs from the first: none."""
    g, canon, store = _prepared(spark, d)
    first = store.table(evaluate_capped_split(canon, store)[0], "first")
    whole = lambda method, **options: lambda: evaluate(g, SHORT, method, **options)
    capped = lambda **options: lambda: evaluate_capped_split(canon, store, **options)[0]
    others: dict[str, Callable[[], DataFrame]] = {
        **{m: whole(m) for m in ("auto", "capped-split", "search", "backward", "two-ended", "fused", "kernel", "kernel-search", "between")},
        **{f"cap {c}": capped(cap=c) for c in (1, 32, "adaptive", None)},
        "pruned": capped(cap=4, prune=True),
        "shortcut": capped(cap=4, shortcut=True),
        "arrays": capped(cap=8, layout="array"),
    }
    assert set(others) - {"auto"} & {*METHODS, *INNER}
    found = {"first": first} | {name: store.table(run(), "other") for name, run in others.items()}
    tagged = reduce(DataFrame.unionByName, (df.select("src", "dst", F.lit(i).alias("m")) for i, df in enumerate(found.values())))
    # all are compared in one pass: how often each pair occurs by each method
    often = tagged.groupBy("src", "dst").agg(*(F.count_if(F.col("m") == i).alias(f"n{i}") for i in range(len(found))))
    sums = [F.sum(c) for i in range(len(found)) for c in (F.col(f"n{i}"), F.abs(F.col(f"n{i}") - F.col("n0")))]
    told = [n or 0 for n in often.agg(*sums).first()]
    return _rows(spark, list(zip(found, told[::2], told[1::2], strict=True)), "method string, pairs long, differing long")


def example_on_handoff(spark, d):
    """The worked expression, with d, e, f and g played by order priorities; it matches the empty path."""
    return evaluate(handoff(spark, d, 450_000), "1-URGENT* (2-HIGH 3-MEDIUM|5-LOW)*")


def co_linked_closure(spark, d):
    """Pages and targets joined by any even number of links, counted: an equivalence among pages, so that its classes tell the
    number of pairs; a target is joined with itself only. Ids of targets are 62-bit hashes, which leave no room for a state."""
    g, store = links(spark, d), Store(spark, "classes")
    edges = store.table(g.edges, "links")
    kind = (F.col("src") % 2).alias("kind")
    classes = kernels.components_in_task(edges, store)
    if classes is None:
        return evaluate(g, "(links ^links)*", "capped-split").groupBy(kind).agg(F.count(F.lit(1)).alias("n_pairs"), F.countDistinct("src").alias("n_src"))
    of = classes.groupBy("class").agg(F.count(F.lit(1)).alias("n"))
    pages = classes.join(of, "class").select(F.col("id").alias("src"), "n")
    targets = edges.select(F.col("dst").alias("src")).distinct().withColumn("n", F.lit(1).cast("long"))
    return store.finish(pages.unionByName(targets).groupBy(kind).agg(F.sum("n").alias("n_pairs"), F.count(F.lit(1)).alias("n_src")))[0]


def co_linked_pages_closure(spark, d):
    """The same between pages alone, whose ids are their own: the pairs of each class, made when they are read."""
    g, store = links(spark, d), Store(spark, "classes")
    classes = kernels.components_in_task(g.edges, store)
    if classes is not None:
        return class_pairs(classes, store)
    pages = _t(spark, d, "pages").select((F.col("page_id") * 2).alias("id"))
    return evaluate(g, "links ^links (links ^links)*", sources=pages)


def sequence_with_nulls(spark, d, partition: tuple[str, ...] = ()):
    """Hand-offs where orders of one status hide their customer: a null keeps its place, and no edge leads over it."""
    o = _t(spark, d, "orders").withColumn("who", F.when(F.col("o_orderstatus") != "P", F.col("o_custkey")))
    return from_sequence(o, list(partition), ["o_orderdate", "o_orderkey"], "who", "o_orderpriority").edges.select("src", "label", "dst")


def links_by_host(spark, d):
    """Links by the host of their page and by the first letter of the target's path."""
    target = F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))))
    rows = _t(spark, d, "pages").select(F.coalesce(F.parse_url("url", F.lit("HOST")), F.lit("")).alias("host"), target.alias("target"))
    return rows.groupBy("host", F.substring(F.lower("target"), 2, 1).alias("letter")).agg(F.count(F.lit(1)).alias("n_links"))


def flow_by_day(spark, d):
    """Edges of the event flow whose property k is below 50, by day and type."""
    e = _t(spark, d, "events")
    low = e.filter(F.get_json_object("props", "$.k").cast("int") < 50)
    kept = from_sequence(low, ["user_id"], ["ts", "event_id"], "event_id", "event_type").edges
    day = e.select(F.col("event_id").alias("src"), F.unix_date(F.col("ts").cast("date")).cast("long").alias("day"))
    return kept.join(day, "src").groupBy("day", "label").agg(F.count(F.lit(1)).alias("n_edges"))


PAIR = ("1-URGENT 3-MEDIUM* 5-LOW", "1-URGENT 2-HIGH* 5-LOW")


def pairs_in_both(spark, d):
    g = handoff(spark, d, 350_000)
    return evaluate(g, PAIR[0]).intersect(evaluate(g, PAIR[1]))


def pairs_in_one(spark, d):
    g = handoff(spark, d, 350_000)
    return evaluate(g, PAIR[0]).exceptAll(evaluate(g, PAIR[1]))


def many_queries_one_graph(spark, d, **options):
    """Three expressions in one evaluation; the last one matches the empty path."""
    return evaluate_many(handoff(spark, d, 350_000), {"one": PAIR[0], "two": PAIR[1], "three": "2-HIGH*"}, **options)


def joined_paths(spark, d):
    g = handoff(spark, d, 350_000)
    return join_paths([(evaluate(g, PAIR[0]), "x", "y"), (evaluate(g, "5-LOW 2-HIGH"), "y", "z")])


def _answers_with_nation(spark, d):
    c = _t(spark, d, "customer").select("c_custkey", "c_nationkey")
    n = _t(spark, d, "nation").select("n_nationkey", "n_regionkey")
    at = c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", F.col("n_regionkey").cast("long").alias("region"), F.col("c_nationkey").cast("long").alias("nation"))
    found = evaluate(handoff(spark, d, 400_000), SHORT)
    return found.join(at, F.col("src") == F.col("c_custkey")).drop("c_custkey")


def answers_by_region_cube(spark, d):
    far = _t(spark, d, "customer").select(F.col("c_custkey").alias("dst"), F.col("c_mktsegment").alias("segment"))
    return _answers_with_nation(spark, d).join(far, "dst").cube("region", "segment").agg(F.count(F.lit(1)).alias("n"))


def answers_rollup(spark, d):
    return _answers_with_nation(spark, d).rollup("region", "nation").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("src").alias("n_src"))


def answers_grouping_sets(spark, d):
    df = _answers_with_nation(spark, d)
    return df.groupingSets([["region"], ["nation"], []], "region", "nation").agg(F.count(F.lit(1)).alias("n"))


def ranked_answers(spark, d):
    deg = degrees(evaluate(handoff(spark, d, 300_000), SHORT, later=True))
    w = Window.orderBy(F.desc("deg"))
    by = deg.groupBy("deg").agg(F.count(F.lit(1)).alias("n_vertices"))
    # ranks run over distinct degrees, at most as many as the largest degree
    total = F.sum("n_vertices").over(w.rowsBetween(Window.unboundedPreceding, -1))
    return by.select("deg", "n_vertices", (F.coalesce(total, F.lit(0)) + 1).alias("rank"), F.dense_rank().over(w).cast("long").alias("dense_rank"))


def flow_in_window(spark, d):
    """Edges of consecutive events of a user that lie within one hour."""
    e = _t(spark, d, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    nxt = e.withColumn("dst", F.lead("event_id").over(w)).withColumn("later", F.lead("ts").over(w))
    return nxt.filter(F.col("later") <= F.col("ts") + F.expr("INTERVAL 1 HOUR")).select(F.col("event_id").alias("src"), F.col("event_type").alias("label"), "dst")


def asof_label(spark, d):
    """For every purchase, the type of the user's latest earlier event that is not a purchase."""
    e = _t(spark, d, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    other = F.when(F.col("event_type") != "purchase", F.col("event_type"))
    return e.withColumn("label", F.last(other, ignorenulls=True).over(w)).filter((F.col("event_type") == "purchase") & F.col("label").isNotNull()).select(F.col("event_id").alias("id"), "label")


def interval_edges(spark, d, minutes: int = 30):
    """(src, dst) of a user's events at most half an hour apart, by a range join on time buckets."""
    width = minutes * 60
    e = _t(spark, d, "events").select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    b = F.floor(F.col("at") / (width * 1_000_000)).cast("long")
    left = e.select("user_id", F.col("event_id").alias("src"), F.col("at").alias("t0"), F.explode(F.array(b, b + 1)).alias("b"))
    right = e.select("user_id", F.col("event_id").alias("dst"), F.col("at").alias("t1"), b.alias("b"))
    close = (F.col("t1") > F.col("t0")) & (F.col("t1") - F.col("t0") <= width * 1_000_000)
    return left.join(right, ["user_id", "b"]).filter(close).select("src", "dst")


def two_rings_entry(spark, d):
    g = two_rings(spark, d)
    found = evaluate(g, "a b* c")
    return _rows(spark, [(g.vertices.count(), g.edges.count(), found.count())], "n_vertices long, n_edges long, out long")


def one_path_entry(spark, d):
    g = one_path(spark, d)
    return _rows(spark, [(g.vertices.count(), g.edges.count(), evaluate(g, "b* c").count())], "n_vertices long, n_edges long, out long")


def two_rings_cost(spark, d):
    """Looks on two rings, counted while they run: lists of the second ring and no walk, against searches from one end and from both."""
    canon = direct(two_rings(spark, d))
    store = Store(spark, "rings")
    told = kernels.in_tasks(canon, store)[1]
    first = canon.starts.count()  # a search looks at the first edge of each start before it walks
    forward = kernels.in_tasks(canon, store, "search", tasks=spark.sparkContext.defaultParallelism)[1]["inspect_search"]
    both = kernels.in_tasks(canon, store, "two-ended")[1]["inspect_search"]
    row = (told["canonical_edges"], told["cap"], told["reach_rows"], told["n_heavy"], told["heavy_sources"], told["inspect_reach"], told["inspect_trail"], forward + first, both)
    return _rows(spark, [row], "n_edges long, cap long, reach_rows long, n_heavy long, heavy_sources long, inspect_reach long, inspect_trail long, inspect_forward long, inspect_two_ended long")


def one_path_cost(spark, d):
    """On a path without an end label no list is ever extended and backward search has no start; forward search walks to the end from every vertex."""
    store = Store(spark, "path")
    canon, _ = canonical_of(one_path(spark, d), "b* c", store)
    told = evaluate_capped_split(canon, store, only="counters")[1]
    back = product_search(canon, store, "backward")[1]["inspect_search"]
    ahead = forward_looks(canon, store)
    return _rows(spark, [(told["inspect_reach"], told["reach_rows"], back, ahead)], "inspect_reach long, reach_rows long, inspect_backward long, inspect_forward long")


def partchain_giant(spark, d):
    """How many answers there are where they are many: tasks count them and write none."""
    return _rows(spark, [(report_only(partchain(spark, d, 36), "R N* A", "kernel-search").out,)], "out long")


def stream_incremental_closure(spark, d):
    """The closure of the urgent hand-offs, from a stream of edges in four micro-batches."""
    e = Store(spark, "batches").table(_urgent(spark, d, 350_000).distinct(), "edges")
    grow = incremental.IncrementalClosure(spark)
    stream = incremental.sliced(e, F.pmod(F.xxhash64("src", "dst"), F.lit(1000)), 4)
    grow.follow(stream, f"{Store(spark, 'follow').root}/checkpoint").awaitTermination()
    return grow.pairs


def stream_window_graphs(spark, d, slide: str | None = None):
    w = incremental.window_edges(incremental.replay(spark, d), "1 hour", slide)
    return incremental.drain(w, "windows", "update", ("start", "label"))


STEPS = "view (view|click)* purchase"


def stream_window_paths(spark, d, slide: str | None = None):
    """Answers of a path query in the graph of every day's window and user."""
    told = incremental.window_paths(incremental.replay(spark, d), STEPS, "1 day", slide)
    return incremental.spread_pairs(incremental.drain(told, "window-paths", "update", ("start", "user_id")))


def stream_session_answers(spark, d):
    """Answers of a path query within every session."""
    told = incremental.session_answers(incremental.replay(spark, d), STEPS, "4 hours")
    return incremental.spread_pairs(incremental.drain(told, "session-answers", "complete"))


def stream_session_paths(spark, d):
    return incremental.drain(incremental.session_paths(incremental.replay(spark, d)), "sessions", "complete")


def stream_user_automaton(spark, d):
    e = incremental.replay(spark, d).select("user_id", "ts", "event_id", "event_type")
    return incremental.drain(incremental.step_automaton(e, STEPS), "stepping", "update", ("user_id",))


def sql_path_query(spark, d, expr: str = "user (assistant user)*"):
    """The table function, one conversation a partition."""
    sqlapi.register(spark)
    turns(spark, d).edges.withColumn("conv", F.floor(F.col("src") / 1000)).createOrReplaceTempView("pathq_turns")
    return spark.sql(f"SELECT src, dst FROM path_query(TABLE(pathq_turns) PARTITION BY (conv), '{expr}')")


def sql_path_matches(spark, d):
    """Conversations by whether their sequence of roles matches an expression."""
    sqlapi.register(spark)
    roles = F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"])
    _t(spark, d, "conversations").groupBy("conv_id").agg(roles.alias("roles")).createOrReplaceTempView("pathq_roles")
    return spark.sql("SELECT conv_id, path_matches(roles, '(user assistant)+') AS matched FROM pathq_roles")


QUERIES: dict[str, Query] = {name: partial(run_workload, name) for name in WORKLOADS} | {
    "automaton_transitions": automaton_transitions,
    "word_expansion": word_expansion,
    "query_classes": query_classes,
    "graph_commerce_profile": commerce_profile,
    "graph_flow_edges": partial(edges_of, flow),
    "graph_handoff_edges": partial(edges_of, partial(handoff, above=300_000)),
    "graph_partchain_edges": partial(edges_of, partial(partchain, least=40)),
    "graph_relay_edges": partial(edges_of, partial(relay, above=150)),
    "graph_turns_edges": partial(edges_of, turns),
    "graph_links_edges": lambda spark, d: links(spark, d).edges.groupBy("src").agg(F.count(F.lit(1)).alias("n_links")),
    "graph_near_edges": partial(edges_of, near),
    "graph_copies_edges": lambda spark, d: copies(spark, d).edges.filter(F.col("label") == "copy"),
    "graph_copies_labels": lambda spark, d: copies(spark, d).label_histogram(),
    "graph_passages_edges": partial(edges_of, passages),
    "label_histogram": label_histogram,
    "degree_histogram": degree_histogram,
    "product_edges_funnel": product_edges_funnel,
    "canonical_sizes": canonical_sizes,
    "reach_counts_capped": reach_counts_capped,
    "light_heavy_classes": light_heavy_classes,
    "light_answers": light_answers_entry,
    "heavy_sources": heavy_sources_entry,
    "trail_counts": trail_counts,
    "heavy_answers": heavy_answers_entry,
    "canonical_direct_route": canonical_direct_route,
    "stored_loops_route": stored_loops_route,
    "handoff_split_rounds": handoff_split_rounds,
    "handoff_split_search": handoff_split_search,
    "flow_dead_end_rounds": flow_dead_end_rounds,
    "flow_dead_end_search": partial(flow_searched, name="flow_dead_end"),
    "flow_until_purchase_search": partial(flow_searched, name="flow_until_purchase"),
    "fixed_cap_1": partial(variant, above=400_000, cap=1),
    "fixed_cap_32": partial(variant, cap=32),
    "complete_lists": partial(variant, cap=None),
    "adaptive_cap": partial(variant, cap="adaptive"),
    "pruned_trail": partial(variant, cap=8, prune=True),
    "light_shortcut": partial(variant, cap=8, shortcut=True),
    "array_layout": partial(variant, cap=8, layout="array"),
    "search_forward": partial(searched, direction="forward"),
    "search_backward": partial(searched, direction="backward"),
    "search_two_ended": partial(searched, direction="both"),
    "search_fused": search_fused,
    "search_inspections": search_inspections,
    "naive_rounds": partial(searched, direction="forward", naive=True, above=400_000),
    "matrix_blocks": matrix_blocks,
    "matrix_closure": matrix_closure_entry,
    "plain_join_word": plain_join_word,
    "sql_recursion": sql_recursion,
    "word_single_label": partial(star_free, expr="lives"),
    "word_repeated_label": word_repeated_label,
    "word_inspections": word_inspections,
    "union_with_epsilon": union_with_epsilon,
    "union_of_words_plain": partial(star_free, expr="(lives|from based) in", plain=True),
    "layered_automaton": layered_automaton,
    "k_path_join": k_path_join,
    "closure_left_rule": partial(closed, rule="left"),
    "closure_right_rule": partial(closed, rule="right"),
    "closure_squaring": partial(closed, rule="squaring"),
    "closure_deep": partial(closed, rule="deep"),
    "closure_inspections": closure_inspections,
    "closure_delta_sizes": closure_delta_sizes,
    "reachable_from_sources": reachable_from_sources,
    "answers_into_targets": answers_into_targets,
    "connected_pairs": connected_pairs,
    "segment_to_segment": segment_to_segment,
    "degrees_sketched": degrees_sketched,
    "targets_by_bitmap": targets_by_bitmap,
    "degree_profile": degree_profile,
    "top_degree_vertices": top_degree_vertices,
    "shortest_length": shortest_length_entry,
    "cost_report": cost_report,
    "run_costs": run_costs,
    "search_report": search_report,
    "bounds_table": bounds_table,
    "regime_exponents": regime_exponents,
    "inspections_by_method": inspections_by_method,
    "bound_checks": bound_checks,
    "gain_by_workload": gain_by_workload,
    "method_agreement": method_agreement,
    "pairs_in_both": pairs_in_both,
    "pairs_in_one": pairs_in_one,
    "many_queries_one_graph": many_queries_one_graph,
    "many_queries_in_rounds": partial(many_queries_one_graph, kernel_limit=0),
    "example_on_handoff": example_on_handoff,
    "co_linked_closure": co_linked_closure,
    "co_linked_pages_closure": co_linked_pages_closure,
    "sequence_with_nulls": sequence_with_nulls,
    "sequence_with_nulls_by_clerk": partial(sequence_with_nulls, partition=("o_orderstatus",)),
    "links_by_host": links_by_host,
    "flow_by_day": flow_by_day,
    "joined_paths": joined_paths,
    "answers_by_region_cube": answers_by_region_cube,
    "answers_rollup": answers_rollup,
    "answers_grouping_sets": answers_grouping_sets,
    "ranked_answers": ranked_answers,
    "flow_in_window": flow_in_window,
    "asof_label": asof_label,
    "interval_edges": interval_edges,
    "two_rings": two_rings_entry,
    "one_path": one_path_entry,
    "two_rings_cost": two_rings_cost,
    "one_path_cost": one_path_cost,
    "partchain_giant": partchain_giant,
    "stream_incremental_closure": stream_incremental_closure,
    "stream_window_tumbling": stream_window_graphs,
    "stream_window_sliding": partial(stream_window_graphs, slide="30 minutes"),
    "stream_window_paths": stream_window_paths,
    "stream_window_paths_sliding": partial(stream_window_paths, slide="12 hours"),
    "stream_session_answers": stream_session_answers,
    "stream_session_paths": stream_session_paths,
    "stream_user_automaton": stream_user_automaton,
    "sql_path_query": sql_path_query,
    "sql_path_query_star": partial(sql_path_query, expr="(user assistant)*"),
    "sql_path_matches": sql_path_matches,
}
