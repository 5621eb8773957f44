"""From an expression and a graph to answers: which method, which physical strategy."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathq.functions.metrics import Probe, RunReport
from pathq.operators import kernels
from pathq.operators.capped_split import Cap, evaluate_capped_split
from pathq.operators.closure import closure_in_tasks, transitive_closure
from pathq.operators.product import Canonical, Packing, product_edges, to_canonical
from pathq.operators.reachable import reachable
from pathq.operators.search import fused_search, searched
from pathq.operators.starfree import evaluate_layered, evaluate_star_free, relations
from pathq.plans.automaton import Automaton, compile_path, disjoint, resolve
from pathq.plans.classify import QueryClass, Word, classify, expand_words
from pathq.plans.expr import Expr, Symbol, as_expr
from pathq.sources.graph import PathGraph
from pathq.store import Store

METHODS = ("auto", "empty", "closure", "star-free", "layered", "capped-split", "search", "backward", "two-ended", "fused", "naive", "kernel", "kernel-search", "component", "component-search")
#: What the planner chooses besides: from given sources, between sources and targets, words by plain joins.
INNER = ("sources", "between", "plain-words")


@dataclass(frozen=True)
class Plan:
    method: str
    reason: str
    query: QueryClass
    automaton: Automaton


def needed_labels(automaton: Automaton, labels: frozenset[str]) -> bool:
    """Whether a graph with only these labels can match a non-empty path."""
    seen, todo = set(automaton.initial), list(automaton.initial)
    while todo:
        q = todo.pop()
        for a, s, p in automaton.transitions:
            if a == q and p not in seen and (s.label in labels if s.but is None else labels - s.but):
                seen.add(p)
                todo.append(p)
    moved = {p for q, s, p in automaton.transitions if q in seen and (s.label in labels if s.but is None else labels - s.but)}
    return bool(moved & automaton.accepting)


@dataclass(frozen=True)
class Facts:
    """What a graph's labels tell: edges, and about how many distinct ends on either side, per label; and the range of ids."""

    edges: dict[str, int]
    sources: dict[str, int]
    targets: dict[str, int]
    ids: tuple[int, int]

    @classmethod
    def of(cls, graph: PathGraph) -> Facts:
        ends = F.approx_count_distinct("src").alias("s"), F.approx_count_distinct("dst").alias("t")
        per = graph.edges.groupBy("label").agg(F.count(F.lit(1)).alias("n"), *ends, F.min(F.least("src", "dst")).alias("lo"), F.max(F.greatest("src", "dst")).alias("hi"))
        rows = per.collect()  # a row per label
        pick = lambda c: {r["label"]: r[c] for r in rows}
        return cls(pick("n"), pick("s"), pick("t"), (min((r["lo"] for r in rows), default=0), max((r["hi"] for r in rows), default=0)))

    def step(self, s: Symbol) -> tuple[int, float]:
        """(edges, edges per vertex that has one) of a symbol; a symbol that stands for several labels has their sums."""
        labels = [s.label] if s.but is None else [x for x in self.edges if x not in s.but]
        n, ends = sum(self.edges.get(x, 0) for x in labels), sum((self.targets if s.backward else self.sources).get(x, 0) for x in labels)
        return n, n / max(1, ends)


def join_rows(words: list[Word], facts: Facts) -> float:
    """The largest intermediate result that joins of these words make, if ends were independent."""
    most = 0.0
    for w in words:
        rows = 0.0
        for i, s in enumerate(w):
            n, degree = facts.step(s)
            rows = float(n) if i == 0 else rows * degree
            most = max(most, rows)
    return most


def choose(
    graph: PathGraph,
    expr: Expr | str,
    sources: DataFrame | None = None,
    component: DataFrame | None = None,
    word_limit: int = 16,
    kernel_limit: int = 200_000,
    targets: DataFrame | None = None,
    facts: Facts | None = None,
    plain_factor: float = 4.0,
) -> Plan:
    """The first rule that fits, from the class of the expression and the facts of the labels.

    ``kernel_limit`` bounds the product edges that one task takes instead of rounds over the cluster; ``plain_factor`` the
    rows that a plain join of words may make, per edge.
    """
    x = as_expr(expr)
    query, automaton = classify(x), compile_path(x)
    facts = facts or Facts.of(graph.restrict_labels(query.labels))
    if not needed_labels(automaton, frozenset(facts.edges)):
        return Plan("empty", "no path can match: a label that every word needs is not in the graph", query, automaton)
    if query.closure_label is not None and sources is None and targets is None:
        return Plan("closure", "a single label repeated", query, automaton)
    if query.star_free:
        try:
            words = expand_words(x, word_limit)[0]
        except OverflowError:
            return Plan("layered", f"star-free, but more than {word_limit} words", query, automaton)
        rows = join_rows(words, facts)
        if rows <= plain_factor * sum(facts.edges.values()):
            return Plan("plain-words", f"{len(words)} words without a star, whose joins make about {rows:.0f} rows", query, automaton)
        return Plan("star-free", f"{len(words)} words without a star", query, automaton)
    if sources is not None and targets is not None:
        return Plan("between", "answers are asked for given sources and targets only", query, automaton)
    if sources is not None:
        return Plan("sources", "answers are asked for given sources only", query, automaton)
    if component is not None:
        return Plan("component", "the graph falls apart by a given key", query, automaton)
    size = sum(facts.step(s)[0] for _, s, _ in automaton.transitions)
    if size <= kernel_limit and not Packing.within(facts.ids, automaton.n_states).wide:
        return Plan("kernel", f"about {size} product edges fit a task", query, automaton)
    # starts and ends are no more than the product edges together
    if 0 < kernel_limit and size <= kernels.LIMIT // 2 and not Packing.within(facts.ids, automaton.n_states).wide:
        return Plan("kernel-search", f"about {size} product edges fit a task, and searches are dealt among tasks", query, automaton)
    return Plan("capped-split", f"about {size} product edges, in rounds over the cluster", query, automaton)


def canonical_of(graph: PathGraph, expr: Expr | str, store: Store | None = None, facts: Facts | None = None) -> tuple[Canonical, Automaton]:
    x = as_expr(expr)
    used = graph.restrict_labels(classify(x).labels)
    automaton = compile_path(x)
    if any(s.but is not None for _, s, _ in automaton.transitions):
        automaton = resolve(automaton, facts.edges if facts else used.labels())
    packing = Packing.within(facts.ids, automaton.n_states) if facts else Packing.of(used, automaton.n_states)
    middle = product_edges(used, automaton, packing)
    return to_canonical(used, automaton, store.table(middle, "product") if store else middle, packing=packing), automaton


def evaluate(graph: PathGraph, expr: Expr | str, method: str = "auto", later: bool = False, **options) -> DataFrame:
    """Distinct (src, dst) joined by a path that matches ``expr``, as a table; all that led to it is removed.

    With ``later``, answers of searches and closures inside tasks are written nowhere: tasks find them when they are read, every
    time anew, from the edges, which stay. For answers that are many times as large as the graph and read once.
    """
    store = Store(graph.spark, "answers")
    found = _run(store, graph, expr, method, only="answers" if later else None, **options)[0]
    return found if store.read_later else store.finish(found)[0]


def evaluate_with_report(graph: PathGraph, expr: Expr | str, method: str = "auto", **options) -> tuple[DataFrame, RunReport]:
    """(answers, report); sizes that the evaluation does not need itself are counted for it."""
    return _reported(graph, expr, method, None, **options)


def report_only(graph: PathGraph, expr: Expr | str, method: str, **options) -> RunReport:
    """The report of a search inside tasks, of complete lists there or of capped lists, which count their answers and write them nowhere."""
    return _reported(graph, expr, method, "counters", **options)[1]


def _reported(graph: PathGraph, expr: Expr | str, method: str, only: str | None, **options) -> tuple[DataFrame | None, RunReport]:
    store, probe = Store(graph.spark, "answers"), Probe(graph.spark)
    found, report, facts, canon, walked = _run(store, graph, expr, method, only=only, **options)
    if only is not None and (found is not None or canon.identity is not None):
        raise ValueError(f"{method} of this expression does not count its answers without writing them")
    answers, out = store.finish(found) if canon is None else (store.table(found, "found") if found is not None else None, None)
    report = replace(report, **probe.read())
    sizes = {"n_vertices": graph.vertices.count(), "n_edges": sum(facts.edges.values()), "n_labels": len(facts.edges)}
    if canon is not None:
        sizes |= {"product_edges": canon.middle.count(), "product_vertices": canon.middle.select(F.explode(F.array("src", "dst")).alias("x")).distinct().count()}
        if report.n_light + report.n_heavy:
            sizes["n_absent"] = sizes["product_vertices"] - report.n_light - report.n_heavy
        if walked is not None:
            sizes["out_states"] = walked.join(canon.ends.select("x").distinct(), "x", "left_semi").count()
        answers, out = store.finish(answers) if answers is not None else (None, report.out)
        if answers is None:
            store.close()
    return answers, replace(report, out=out, **sizes)


def _run(
    store: Store,
    graph: PathGraph,
    expr: Expr | str,
    method: str = "auto",
    cap: Cap = "sqrt",
    sources: DataFrame | None = None,
    targets: DataFrame | None = None,
    component: DataFrame | None = None,
    kernel_limit: int = 200_000,
    row_budget: int = 10**11,
    only: str | None = None,
    **options,
) -> tuple[DataFrame, RunReport, Facts, Canonical | None, DataFrame | None]:
    """(answers, counters, facts, canonical form or None, visited (s, x) of a search or None).

    ``sources`` and ``targets`` (id) restrict answers and are pushed into the seeds of searches. ``row_budget`` bounds the
    rows of capped lists. ``only`` ("answers", "counters") is what searches inside tasks are asked for.
    """
    spark, x = graph.spark, as_expr(expr)
    query = classify(x)
    pruned = graph.restrict_labels(query.labels)
    # written once: sequences and links are costly to derive, and several steps read them
    used = PathGraph(store.table(pruned.edges, "edges"), pruned.wider, pruned.base)
    facts = Facts.of(used)
    chosen = method == "auto"
    if chosen:
        method = choose(used, x, sources, component, kernel_limit=kernel_limit, targets=targets, facts=facts).method
        options = options if method != "closure" else {"rule": "tasks"} | options
    if method not in (*METHODS, *INNER):
        raise ValueError(f"method {method!r} is none of {METHODS}")
    report = RunReport(query=expr if isinstance(expr, str) else "", method=method)
    if method == "empty":
        found = spark.createDataFrame([], "src long, dst long")
        if query.nullable:
            found = graph.vertices.select(F.col("id").alias("src"), F.col("id").alias("dst"))
        return _only(found, sources, targets), report, facts, None, None
    if method == "closure":
        s = query.closure_label
        if s is None:
            raise ValueError("not a single label repeated")
        e = relations(used, (s,))[0].select(F.col("p").alias("src"), F.col("q").alias("dst"))
        if only == "answers" and options.get("rule") == "tasks":
            told = closure_in_tasks(e, store, graph.vertices if query.reflexive else None, only)
            if told is not None:
                store.read_later = True
                return _only(told[0], sources, targets), report, facts, None, None
        found, log = transitive_closure(e, store, options.get("rule", "delta"), graph.vertices if query.reflexive else None)
        return _only(found, sources, targets), replace(report, inspect_closure=log.inspected, rounds=log.rounds), facts, None, None
    if method in ("star-free", "plain-words"):
        found, told = evaluate_star_free(used, x, store, cap="adaptive" if cap == "sqrt" else cap, plain=method == "plain-words", **options)
        return _only(found, sources, targets), _filled(report, told), facts, None, None
    if method == "layered":
        found, told = evaluate_layered(used, x, store)
        return _only(found, sources, targets), _filled(report, told), facts, None, None
    if method == "fused":
        found, told = fused_search(used, resolve(compile_path(x), facts.edges), store)
        return _only(found, sources, targets), _filled(report, told), facts, None, None
    canon, automaton = canonical_of(used, x, store, facts)
    report, walked = replace(report, automaton_size=automaton.size), None
    if method == "sources":
        return _only(reachable(canon, sources, store), None, targets), report, facts, canon, None
    canon = canon.seeded(sources, targets)
    if chosen and method == "kernel-search" and canon.identity is None:
        store.read_later = only == "answers"
    if method == "kernel" and cap is None and only == "counters":
        found, told = kernels.complete_lists(canon, store, only)
    elif method in ("kernel", "kernel-search"):
        searches = {} if method == "kernel" else {"method": "search", "tasks": spark.sparkContext.defaultParallelism, "only": only if only == "counters" or store.read_later else None}
        found, told = kernels.in_tasks(canon, store, cap=cap, **searches)
    elif method in ("component", "component-search"):
        if component is None:
            raise ValueError("the component strategy needs a key per vertex")
        # a vertex's part holds for all its product vertices
        states = F.explode(F.array(*[F.lit(q) for q in range(automaton.n_states)]))
        spread = component.select("id", "part", states.alias("q")).select(canon.packing.pack(F.col("id"), F.col("q")).alias("id"), "part")
        found, told = kernels.by_part(canon, spread, store, "split" if method == "component" else "search", cap, only if only == "counters" and method == "component-search" else None)
    elif method == "capped-split":
        found, told = evaluate_capped_split(canon, store, cap, most_rows=row_budget, only=only, **options)
    else:
        direction = {"search": "forward", "naive": "forward", "backward": "backward", "two-ended": "both", "between": "both"}[method]
        found, told, walked = searched(canon, store, direction, naive=method == "naive")
        walked = walked if direction == "forward" else None
    return found, _filled(report, told), facts, canon, walked


def _filled(report: RunReport, told: dict[str, int]) -> RunReport:
    return replace(report, **{k: int(v) for k, v in told.items() if hasattr(report, k) and k not in ("query", "method")})


def _only(found: DataFrame, sources: DataFrame | None, targets: DataFrame | None) -> DataFrame:
    if sources is not None:
        found = found.join(sources.select(F.col("id").alias("src")).distinct(), "src", "left_semi")
    if targets is not None:
        found = found.join(targets.select(F.col("id").alias("dst")).distinct(), "dst", "left_semi")
    return found.select("src", "dst")


def evaluate_many(graph: PathGraph, queries: dict[str, Expr | str], cap: Cap = "sqrt", kernel_limit: int = 200_000) -> DataFrame:
    """Distinct (query, src, dst) of several expressions, in one evaluation over the product with the union of their automata.

    Lists, rounds and walks are shared. A start is named by its product vertex, whose state tells the query apart.
    """
    store = Store(graph.spark, "many")
    names = sorted(queries)
    labels = [classify(queries[n]).labels for n in names]
    pruned = graph if None in labels else graph.restrict_labels(frozenset().union(*labels))
    used = PathGraph(store.table(pruned.edges, "edges"), pruned.wider, pruned.base)
    facts = Facts.of(used)
    whole, first, _ = disjoint([resolve(compile_path(queries[n]), facts.edges) for n in names])
    packing = Packing.within(facts.ids, whole.n_states)
    canon = to_canonical(used, whole, store.table(product_edges(used, whole, packing), "product"), packing=packing)
    shared = Canonical(canon.starts.select(F.col("x").alias("s"), "x"), canon.middle, canon.ends, None, packing)
    small = not packing.wide and sum(facts.step(s)[0] for _, s, _ in whole.transitions) <= kernel_limit
    found = kernels.in_tasks(shared, store, cap=cap)[0] if small else evaluate_capped_split(shared, store, cap)[0]
    which = F.element_at(F.create_map(*[F.lit(v) for name, states in zip(names, first, strict=True) for q in sorted(states) for v in (q, name)]), packing.state(F.col("src")).cast("int"))
    out = found.select(which.alias("query"), packing.vertex(F.col("src")).alias("src"), "dst")
    for name in names:
        if classify(queries[name]).nullable:
            out = out.unionByName(graph.vertices.select(F.lit(name).alias("query"), F.col("id").alias("src"), F.col("id").alias("dst")))
    return store.finish(out.distinct())[0]


def join_paths(parts: list[tuple[DataFrame, str, str]]) -> DataFrame:
    """Conjunction of path queries: each (answers, variable of src, variable of dst), joined on shared variables."""
    out = None
    for answers, a, b in parts:
        df = answers.filter(F.col("src") == F.col("dst")).select(F.col("src").alias(a)) if a == b else answers.select(F.col("src").alias(a), F.col("dst").alias(b))
        if out is None:
            out = df
            continue
        shared = [c for c in df.columns if c in out.columns]
        if not shared:
            raise ValueError(f"{a}, {b} share no variable with the parts before")
        out = out.join(df, shared)
    return out.distinct()


def explain_path(graph: PathGraph, expr: Expr | str, **options) -> str:
    """Class, automaton and chosen strategy of a query, with the numbers that led to it."""
    plan = choose(graph, expr, **options)
    a, lines = plan.automaton, [f"class: {plan.query.name}{', matches the empty path' if plan.query.nullable else ''}"]
    lines.append(f"automaton: {a.n_states} states, initial {sorted(a.initial)}, accepting {sorted(a.accepting)}")
    for q, s, p in sorted(a.transitions, key=lambda t: (t[0], t[2], t[1].label or "")):
        lines.append(f"  {q} --{'^' if s.backward else ''}{s.label if s.but is None else '!' + '|'.join(sorted(s.but)) if s.but else '_'}--> {p}")
    lines.append(f"labels: {'any' if plan.query.labels is None else ', '.join(sorted(plan.query.labels))}")
    lines.append(f"method: {plan.method} ({plan.reason})")
    return "\n".join(lines)
