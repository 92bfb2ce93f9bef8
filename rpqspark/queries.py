"""All registered queries of the path engine and their SQL."""

from __future__ import annotations

import dataclasses
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .automaton.bitparallel import match_words
from .baselines import alp, closure, joins, pernode, product, rcte
from .exec import fastpaths, pairs, planner, rare, seek
from .exec.options import RpqOptions
from .graph import encode, sources, stats
from .graph.model import Graph
from .index import cyclic, space, wavelet
from .lang import patterns
from .lang.parser import parse
from .metrics import bench, cost
from .ops.relational import ENTRIES
from .sql import bgp, surface
from .sql import udtf as functions
from .stream import events as stream
from .workload import log, oracle
from .workload.table1 import QUERIES

Query = Callable[[SparkSession, str], DataFrame]
FRONTIER = RpqOptions(executor="frontier", fast_paths=False)


def workload(query_id: str, **options) -> Query:
    q = QUERIES[query_id]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return planner.evaluate(sources.load(spark, sf_dir, q.graph), q.path, q.s, q.o, RpqOptions(**options))

    return run


def on(query_id: str, f) -> Query:
    """A baseline on a workload query: f(graph, query) gives pairs (s, o)."""
    q = QUERIES[query_id]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = f(sources.load(spark, sf_dir, q.graph), q)
        return out.select(*[c for c, v in (("s", q.s), ("o", q.o)) if v is None])

    return run


def on_graph(name: str, f) -> Query:
    return lambda spark, sf_dir: f(sources.load(spark, sf_dir, name))


# ---- words of events -------------------------------------------------------------------
WORDS = {"purchase": "(view|click)*/purchase", "clicks": "view*/click+", "browse": "(view|click|error)+", "signup": "signup/(view|click|purchase|signup|error)*/purchase"}
_LETTERS = {"purchase": "[vc]*p", "clicks": "v*c+", "browse": "[vce]+", "signup": "s[vcpse]*p"}


def words(name: str) -> Query:
    def run(spark, sf_dir):
        e = sources.table(spark, sf_dir, "events").withColumn("day", F.date_format("ts", "yyyy-MM-dd"))
        return match_words(e, ["user_id", "day"], ["ts", "event_id"], "event_type", parse(WORDS[name]))

    return run


def words_sql(name: str) -> str:
    return f"""SELECT user_id, day, count(*) AS n, regexp_full_match(string_agg(left(event_type, 1), '' ORDER BY ts, event_id), '{_LETTERS[name]}') AS accepted
        FROM (SELECT *, strftime(ts, '%Y-%m-%d') AS day FROM events) GROUP BY user_id, day"""


# ---- index -----------------------------------------------------------------------------
def metro_numbers(spark: SparkSession) -> DataFrame:
    """The worked example with the numbers of its printed index."""
    node = {"SA": 1, "UCh": 2, "LH": 3, "BA": 4, "Baq": 5}
    label = {"l1": 1, "l2": 2, "l5": 3, "bus": 4}
    rows = []
    for s, p, o in sources.METRO:
        rows += [(node[s], label[p], node[o]), (node[o], label[p] if p != "bus" else 5, node[s])]
    return spark.createDataFrame(rows, "s long, p long, o long")


def index_columns(spark, sf_dir):
    """Last columns and starts of the worked example."""
    i = cyclic.build(metro_numbers(spark))
    out = None
    for c, df in i.columns.items():
        part = df.join(i.starts[c], "symbol").select(F.lit(c).alias("col"), "pos", "symbol", "rank", "start")
        out = part if out is None else out.unionByName(part)
    return out


def index_triples(spark, sf_dir):
    """All edges of a graph, taken back from the index by three steps each."""
    e = encode.encode(sources.load(spark, sf_dir, "chat"))
    i = cyclic.build(e.edges)
    back = i.triple_at(i.columns["p"].select("pos"))
    names = e.labels.select(F.col("id").cast("long").alias("p"), F.col("name"))
    return e.decode(back, "s", "o").join(F.broadcast(names), "p").select("s", F.col("name").alias("p"), "o")


def index_backward(spark, sf_dir):
    """Edges into each object by label, by a backward step from the object's range."""
    e = encode.encode(sources.load(spark, sf_dir, "web"))
    i = cyclic.build(e.edges)
    ranges = i.object_range(e.nodes.select(F.col("id").alias("node")))
    got = i.backward(i.symbols_of(ranges, "p"), "p")
    out = got.join(ranges, ["b", "e"]).select(F.col("node").alias("o"), F.col("symbol").alias("p"), (F.col("ne") - F.col("nb") + 1).alias("n"))
    names = e.labels.select(F.col("id").cast("long").alias("p"), F.col("name"))
    return e.decode(out, "o").join(F.broadcast(names), "p").select("o", F.col("name").alias("p"), "n")


def index_interval(spark, sf_dir):
    """Edges of an interval of objects, and of one of labels, from the counts alone."""
    e = encode.encode(sources.load(spark, sf_dir, "web"))
    i = cyclic.build(e.edges)
    parts = []
    for what, names, col, lo, hi in (("objects", e.nodes, "o", "host:a", "host:n"), ("labels", e.labels, "p", "in_lang", "on_host")):
        ids = names.filter((F.col("name") >= lo) & (F.col("name") <= hi)).agg(F.min("id").alias("lo"), F.max("id").alias("hi")).first()
        parts.append(i.interval(ids.lo, ids.hi, col).select(F.lit(what).alias("what"), (F.col("e") - F.col("b") + 1).alias("n")))
    return parts[0].unionByName(parts[1])


def level_ranks(spark, sf_dir):
    """Rank by words on the level table of the subjects' column of a completed graph, at every fifth position."""
    from .exec.store import Store

    e = encode.encode(sources.load(spark, sf_dir, "chat"))
    column = cyclic.build(encode.complete(e.edges, e.n_labels()), ("s",)).columns["s"].select("pos", (F.col("symbol") - 1).alias("symbol"))
    height = max(1, (e.nodes.count() - 1).bit_length())
    t = wavelet.level_table(column, height, Store(spark, "levels"))
    n = column.count()
    asked = spark.range(0, n, 5).select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(0), F.lit(height - 1))).alias("level"))
    return wavelet.ranks(t, asked)


def space_report(spark, sf_dir):
    return space.report(encode.encode(sources.load(spark, sf_dir, "trade"))).select("component", F.round("bytes_per_edge", 6).alias("bytes_per_edge"))


# ---- measures --------------------------------------------------------------------------
def run_counters(spark, sf_dir):
    """Work of the frontier executor on a closure over the tree of hosts."""
    return cost.counters(sources.load(spark, sf_dir, "web"), QUERIES["w01"].path, o="host:com")[0]


def ring_counters(spark, sf_dir):
    """Work of the index executor on the same: search steps, ranges of labels met, subjects entered."""
    from .automaton import bitparallel
    from .exec import ring

    shard = ring.shard_of(sources.load(spark, sf_dir, "web"), RpqOptions().kernel_edges)
    search = ring.Search(shard, bitparallel.compile(parse(QUERIES["w01"].path)))
    at = list(shard.names).index("host:com")
    n = len(search.run(at, at + 1))
    return spark.createDataFrame([(search.counts["subjects"], n)], "subjects long, answers long")


#: The query that an event of a type stands for: (subject is its user, path, object is its user), and its pattern.
ASKED = {
    "view": (False, "view/click*", True, "v /* c"), "click": (False, "click*", True, "v * c"), "error": (False, "error+", True, "v + c"),
    "signup": (True, "signup*", False, "c * v"), "purchase": (False, "click/purchase", False, "v / v"),
}


def asked(events: DataFrame) -> DataFrame:
    """(s, path, o): a log with a query for each event of a known type."""
    user, kind = F.concat(F.lit("user:"), F.coalesce(F.col("user_id").cast("string"), F.lit(""))), F.col("event_type")
    of = lambda i: [t for t, q in ASKED.items() if q[i]]
    path = F.create_map(*[F.lit(x) for t, q in ASKED.items() for x in (t, q[1])])[kind]
    return events.filter(kind.isin(list(ASKED))).select(F.when(kind.isin(of(0)), user).alias("s"), path.alias("path"), F.when(kind.isin(of(2)), user).otherwise("?y").alias("o"))


def histogram(spark, sf_dir):
    """Patterns of a log of queries, one for each event."""
    return patterns.pattern_histogram(asked(sources.table(spark, sf_dir, "events")))


def clean_log(spark, sf_dir):
    rows = [("?a", "parent*", "host:example.com"), ("?b", "parent *", "host:example.com"), ("?x", "parent", "?y"), ("?x", "on_host/parent*", "host:nowhere"), ("page:0", "on_host/parent*", "?z"), ("?x", "on_host|(", "?y")]
    g = sources.load(spark, sf_dir, "web")
    return log.clean(spark.createDataFrame(rows, "s string, path string, o string"), g.nodes())


def log_graphs(spark, sf_dir) -> dict[str, Graph]:
    return {n: sources.load(spark, sf_dir, n) for n in sorted({q.graph for _, _, q, _ in log.models()})}


def log_answers(spark, sf_dir, method: str = "core"):
    """All queries of the synthetic log, keyed by their constants, with the number of answers of each."""
    return log.answers(log_graphs(spark, sf_dir), method=method)


def timed_log(spark, sf_dir):
    """A query of every pattern by two methods, timed, and what the summaries say, times left out.

    Every run goes to its end, without limits, and the index is searched as such whatever the graph's size.
    """
    graphs = log_graphs(spark, sf_dir)
    some = [x for x in log.generate(graphs, 20) if x[0].endswith(".0")]
    some = [x for i, x in enumerate(some) if QUERIES[x[0].split(".")[0]].pattern not in {QUERIES[y[0].split(".")[0]].pattern for y in some[:i]}]
    whole = RpqOptions(index_only=True)
    runs = log.run(spark, graphs, some, "core", whole).unionByName(log.run(spark, graphs, some, "ring", whole))
    best = bench.winners(runs).groupBy().agg(F.count("*").alias("patterns"), F.round(F.sum("share"), 6).alias("share"))
    done = runs.groupBy().agg(F.countDistinct("query").alias("queries"), F.countDistinct("method").alias("methods"), F.count_if(F.col("answers").isNull()).alias("timeouts"))
    same = runs.groupBy("query").agg(F.countDistinct("answers").alias("n")).groupBy().agg(F.max("n").alias("answers_a_query"))
    return best.crossJoin(done).crossJoin(same)


def useful(spark, sf_dir):
    from .automaton import bitparallel

    return pairs.useful_sources(sources.load(spark, sf_dir, "web"), bitparallel.compile(parse("on_host/parent+")), RpqOptions())


def filtered_nodes(spark, sf_dir):
    """Paths whose first host must have a name of some kind."""
    g = sources.load(spark, sf_dir, "web")
    ok = g.nodes().filter(F.col("node").rlike(_HOSTS))
    return planner.evaluate(g, "on_host/parent/parent", o="host:com", node_filter={1: ok})


_HOSTS = "^host:(the|thth)"


def filtered_pairs(spark, sf_dir):
    g = sources.load(spark, sf_dir, "web")
    ok = g.nodes().filter(F.col("node").rlike(_HOSTS))
    return planner.evaluate(g, "on_host/parent+", node_filter={1: ok})


def meet_must_pass(spark, sf_dir):
    """For some nations, whether an order's customer lives there: both ends constant, searched from both."""
    g = sources.load(spark, sf_dir, "trade")
    out = None
    for nation, region in ((2, 0), (3, 1), (19, 3)):
        found = planner.evaluate(g, f"^lives_in/lives_in/@nation:{nation}/in_region", f"nation:{nation}", f"region:{region}", dataclasses.replace(FRONTIER, bidirectional=True))
        part = found.select(F.lit(nation).alias("nation"), "found")
        out = part if out is None else out.unionByName(part)
    return out


def set_to_constant(spark, sf_dir):
    g = sources.load(spark, sf_dir, "web")
    return planner.evaluate(g, "on_host/parent*", s="page:5", o_set=spark.createDataFrame([("host:com",), ("host:org",), ("host:net",)], "node string"))


def sql_subquery(spark, sf_dir):
    """An equality in a subquery over another table binds nothing of the call."""
    sources.load(spark, sf_dir, "trade").edges.createOrReplaceTempView("trade_graph")
    return surface.sql(spark, "SELECT t.s, t.o FROM rpq(graph => 'trade_graph', path => 'lives_in/in_region') t JOIN (SELECT o AS k FROM trade_graph WHERE s = 'nation:3' AND p = 'in_region') q ON t.o = q.k")


def from_set(spark, sf_dir):
    g = sources.load(spark, sf_dir, "web")
    return planner.evaluate(g, "on_host/parent*", o_set=spark.createDataFrame([("host:com",), ("host:org",)], "node string"))


def completed(f, name: str, last=lambda df: df) -> Query:
    """An aggregate over a file stream of events, run to its end; its whole state is written after each batch."""

    def run(spark, sf_dir):
        import uuid

        from .exec.store import Store

        static = sources.table(spark, sf_dir, "events")
        store, table = Store(spark, "stream"), f"{name}_{uuid.uuid4().hex}"
        static.repartition(4).write.parquet(store.path("in"))
        out = f(stream.source(spark, store.path("in"), static.schema, 2))
        write = lambda df, _: df.write.mode("overwrite").parquet(store.path("out"))
        out.writeStream.foreachBatch(write).option("checkpointLocation", store.path("state")).outputMode("complete").queryName(table).trigger(availableNow=True).start().awaitTermination()
        return last(spark.read.schema(out.schema).parquet(store.path("out")))

    return run


def streamed(f, name: str) -> Query:
    """An operator over a file stream of events, run to its end."""

    def run(spark, sf_dir):
        import uuid

        from .exec.store import Store

        static = sources.table(spark, sf_dir, "events")
        store, table = Store(spark, "stream"), f"{name}_{uuid.uuid4().hex}"
        static.repartition(3).write.parquet(store.path("in"))
        out = f(stream.source(spark, store.path("in"), static.schema, 10))
        q = out.writeStream.format("parquet").option("path", store.path("out")).option("checkpointLocation", store.path("state")).outputMode("append").queryName(table).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(out.schema).parquet(store.path("out"))

    return run


def sql_call(spark, sf_dir):
    g = sources.load(spark, sf_dir, "trade")
    g.edges.createOrReplaceTempView("trade_graph")
    return surface.sql(spark, "SELECT t.s AS customer, count(*) AS n FROM rpq(graph => 'trade_graph', path => '^placed_by/has_part/of_brand') t WHERE t.o = 'brand:Brand#17' GROUP BY t.s")


def local_turns(spark, sf_dir):
    """A small graph per conversation, searched by a lateral table function."""
    functions.register(spark)
    c = sources.load(spark, sf_dir, "chat").edges.withColumn("c", F.regexp_extract("s", r"turn:(\d+)\.", 1))
    c.groupBy("c").agg(F.collect_list("s").alias("s"), F.collect_list("p").alias("p"), F.collect_list("o").alias("o")).createOrReplaceTempView("chat_arrays")
    return spark.sql("SELECT t.s, t.o FROM chat_arrays a, LATERAL rpq_local(a.s, a.p, a.o, 'user/assistant') t")


def accepted_words(spark, sf_dir):
    functions.register(spark)
    e = sources.table(spark, sf_dir, "events").groupBy("user_id", F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda x: x["event_type"]).alias("w"))
    return e.select("user_id", "day", F.size("w").cast("long").alias("n"), F.expr(f"rpq_accepts(w, '{WORDS['clicks']}')").alias("accepted"))


def incremental(spark, sf_dir):
    from .stream.incremental import Incremental

    g = sources.load(spark, sf_dir, "web")
    half = F.pmod(F.xxhash64("s", "o"), F.lit(2)) == 0
    i = Incremental(Graph(g.edges.filter(half)), "on_host/parent*", "host:com")
    i.add(g.edges.filter(~half))
    return i.answers()


#: Queries of the workload that are asked on the index too.
RING = ("w01", "w02b", "w05", "w07", "w12", "w13", "w14", "w21", "w22")


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {f"graph_{n}": on_graph(n, lambda g: g.edges) for n in ("trade", "flow", "pulse", "web", "chat", "succ", "docs", "knn")}
    out |= {f"rpq_{i}": workload(i) for i in QUERIES}
    one = lambda q: {"s": q.s, "o": q.o}
    out |= {
        "rpq_frontier_to": workload("w02b", executor="frontier"),
        "rpq_frontier_from": workload("w05", executor="frontier"),
        "rpq_frontier_pairs": workload("w13", executor="frontier"),
        "rpq_frontier_objects": workload("w13", executor="frontier", order="objects", direction="fixed", prune=False),
        "rpq_frontier_wide": workload("w17", executor="frontier", mask_bits=2),
        "rpq_frontier_found": workload("w21", executor="frontier", fast_paths=False),
        "rpq_frontier_meet": workload("w21", executor="frontier", fast_paths=False, bidirectional=True),
        "rpq_no_fast_path": workload("w08", fast_paths=False),
        "rpq_no_pruning": workload("w01", executor="frontier", label_pruning=False, merge_states=False),
        "rpq_useful_sources": useful,
        "rpq_from_set": from_set,
        "rpq_node_filter": filtered_nodes,
        "rpq_node_filter_pairs": filtered_pairs,
        "rpq_meet_must_pass": meet_must_pass,
        "rpq_set_to_constant": set_to_constant,
        "rpq_sql_subquery": sql_subquery,
        "rpq_pattern_same_variable": on_graph("flow", lambda g: bgp.evaluate(g, [("?x", "error/click", "?x"), ("?x", "view", "?y")])),
        "rpq_unknown_self": on_graph("web", lambda g: planner.evaluate(g, "parent*", s="host:nowhere", options=RpqOptions(zero_length_unknown="self"))),
        "rpq_limited": on_graph("web", lambda g: planner.evaluate(g, "on_host/parent*", options=dataclasses.replace(FRONTIER, limit=25)).agg(F.count("*").alias("n"))),
        "rpq_no_visited": workload("w17", executor="frontier", visited_pruning=False),
        "rpq_no_range_start": workload("w13", executor="frontier", range_start=False),
        "rpq_forward": workload("w21", executor="frontier", fast_paths=False, direction="forward"),
        "rpq_next_by_ranges": on_graph("web", lambda g: seek.next_solution(g, "on_host/parent*", "s", "page:5", o="host:com", options=RpqOptions(executor="ring"))),
        "rpq_must_pass": on_graph("trade", lambda g: planner.evaluate(g, "placed_by/lives_in/@nation:3/in_region")),
        "rpq_negated": on_graph("pulse", lambda g: planner.evaluate(g, "!(error_3|click_1)/click_1+", o="user:7")),
        "rpq_same_variable": on_graph("flow", lambda g: planner.evaluate(g, "error/click", s="?x", o="?x")),
        "rpq_rare_split": on_graph("web", lambda g: rare.split_evaluate(g, "on_host/parent/parent*", "on_host")),
        "rpq_rare_auto": on_graph("pulse", lambda g: planner.evaluate(g, "error_3+/signup_2/click_1+", options=dataclasses.replace(FRONTIER, rare_times=1))),
        "rpq_depth_first": workload("w05", executor="kernel", visit="dfs"),
        "rpq_next_solution": on_graph("web", lambda g: seek.next_solution(g, "on_host/parent*", "s", "page:5", o="host:com")),
        "rpq_pattern_join": on_graph("trade", lambda g: bgp.evaluate(g, [("?c", "lives_in", "nation:3"), ("?o", "placed_by", "?c"), ("?o", "has_part/supplied_by", "?s"), ("?s", "based_in/in_region?", "?r")])),
        "rpq_sql": sql_call,
        "rpq_local_function": local_turns,
        "rpq_accepts_function": accepted_words,
        "fast_single": on_graph("trade", lambda g: fastpaths.single(g, parse("placed_by"))),
        "fast_alternation": on_graph("trade", lambda g: fastpaths.alternation(g, [parse("lives_in"), parse("^based_in")])),
        "fast_concat": on_graph("trade", lambda g: fastpaths.concat2(g, parse("lives_in"), parse("in_region"))),
        "base_product": on("w01", lambda g, q: product.evaluate(g, q.path, o=q.o)),
        "base_materialised": on("w05", lambda g, q: product.evaluate(g, q.path, q.s, materialised=True)),
        "base_subset": on("w05", lambda g, q: product.evaluate(g, q.path, q.s, automaton="subset")),
        "base_epsilon": on("w05", lambda g, q: product.evaluate(g, q.path, q.s, automaton="epsilon")),
        "base_operators": on("w13", lambda g, q: alp.evaluate(g, q.path)),
        "base_per_node": on("w17", lambda g, q: pernode.evaluate(g, q.path, o=q.o)),
        "base_per_node_all": on("w13", lambda g, q: pernode.evaluate(g, q.path)),
        "base_semi_naive": on_graph("web", lambda g: closure.semi_naive(fastpaths.single(g, parse("parent")))),
        "base_squaring": on_graph("web", lambda g: closure.squaring(fastpaths.single(g, parse("parent")))),
        "base_joins": on_graph("trade", lambda g: joins.evaluate(g, "^placed_by/has_part").groupBy("s").agg(F.count("*").alias("paths"), F.countDistinct("o").alias("parts"))),
        "base_recursive_sql": on("w05", lambda g, q: rcte.evaluate(g, q.path, q.s)),
        "index_columns": index_columns,
        "index_triples": index_triples,
        "index_backward": index_backward,
        "wavelet_ranks": level_ranks,
        "encode_edges": on_graph("chat", lambda g: (lambda e: e.decode(e.edges.join(e.labels.select(F.col("id").alias("p"), "name"), "p").select("s", F.col("name").alias("p"), "o"), "s", "o").select("s", "p", "o"))(encode.encode(g))),
        "complete_edges": on_graph("chat", lambda g: g.completed()),
        "graph_stats": on_graph("trade", stats.stats),
        "graph_label_counts": on_graph("trade", stats.label_counts),
        "graph_selectivity": on_graph("trade", stats.distinct_in_range),
        "graph_labels_into": on_graph("web", lambda g: stats.labels_into(g, "host:a", "host:n")),
        "graph_sources_of": on_graph("web", lambda g: stats.sources_of(g, ["parent", "on_host"])),
        "measure_product": on_graph("pulse", lambda g: cost.product_size(g, "error_3+", o="user:7").select("product_nodes")),
        "measure_counters": run_counters,
        "measure_space": space_report,
        "measure_winners": timed_log,
        "measure_ring": ring_counters,
        "log_answers": log_answers,
        "index_interval": index_interval,
        "log_patterns": histogram,
        "log_clean": clean_log,
        "stream_windows": completed(stream.windowed, "windows", lambda d: d.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")),
        "stream_sessions": completed(lambda e: stream.sessions(e, late="60 days"), "sessions", lambda d: d.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))),
        "stream_purchases": streamed(stream.purchases_after_clicks, "purchases"),
        "stream_deduplicated": streamed(lambda e: stream.deduplicated(e, "60 days").select("event_id"), "dedup"),
        "stream_matches": streamed(lambda e: stream.matches(e, "click/purchase"), "matches"),
        "stream_incremental": incremental,
        "stream_labelled": streamed(lambda e: stream.labelled(e, e.sparkSession.createDataFrame([("click", 1), ("purchase", 2)], "name string, id int")), "labelled"),
        "rpq_near": on_graph("knn", lambda g: planner.evaluate(g, "near_3/near_3+")),
        "rpq_same_text": on_graph("docs", lambda g: planner.evaluate(g, "same_text+/quality")),
    }
    out |= {f"ring_{i}": workload(i, executor="ring", fast_paths=False) for i in RING}
    out |= {f"automaton_{n}": words(n) for n in WORDS}
    return out | {n: e[0] for n, e in ENTRIES.items()}


def _pairs(graph: str, transitions: str, finals: str, last: str = "SELECT DISTINCT origin AS s, node AS o", s=None, o=None, where: str = "") -> str:
    return oracle.recursion(graph, transitions, finals, s, o, f"{last} FROM reach WHERE q IN ({finals}) {where}")


def oracle_sql() -> dict[str, str]:
    g = oracle.GRAPHS
    # Columns, ranks and starts of the worked example's printed index.
    columns = {"o": [3, 4, 2, 4, 3, 5, 4, 1, 2, 1, 1, 5, 1, 2, 2, 4], "s": [3, 5, 2, 2, 3, 1, 4, 1, 5, 4, 4, 1, 2, 2, 4, 1], "p": [5, 2, 3, 4, 4, 1, 5, 1, 2, 1, 3, 5, 4, 3, 1, 3]}
    starts = {"o": [0, 4, 8, 10, 14], "s": [0, 4, 8, 10, 14], "p": [0, 4, 6, 10, 13]}
    rows = ", ".join(f"('{c}', {i + 1}, {x}, {seq[: i + 1].count(x)}, {starts[c][x - 1]})" for c, seq in columns.items() for i, x in enumerate(seq))
    out = {f"graph_{n}": f"SELECT s, p, o FROM ({sql})" for n, sql in g.items()}
    out |= {f"rpq_{i}": oracle.of(i) for i in QUERIES}
    out |= {f"ring_{i}": oracle.of(i) for i in RING}
    for name, i in {"rpq_frontier_to": "w02b", "rpq_frontier_from": "w05", "rpq_frontier_pairs": "w13", "rpq_frontier_objects": "w13", "rpq_frontier_wide": "w17", "rpq_frontier_found": "w21", "rpq_frontier_meet": "w21", "rpq_no_fast_path": "w08", "rpq_no_pruning": "w01", "base_product": "w01", "base_materialised": "w05", "base_subset": "w05", "base_epsilon": "w05", "base_operators": "w13", "base_per_node": "w17", "base_per_node_all": "w13", "base_recursive_sql": "w05", "stream_incremental": "w01", "rpq_no_visited": "w17", "rpq_no_range_start": "w13", "rpq_forward": "w21", "rpq_depth_first": "w05"}.items():
        out[name] = oracle.of(i)
    parent = _pairs("web", "0 parent 1, 1 parent 1", "1")
    out |= {
        "rpq_useful_sources": _pairs("web", "0 on_host 1, 1 parent 2, 2 parent 2", "2", "SELECT DISTINCT origin AS node"),
        "rpq_from_set": _pairs("web", "0 on_host 1, 1 parent 1", "1", "SELECT DISTINCT origin AS s", where="AND node IN ('host:com', 'host:org')"),
        "rpq_node_filter": f"WITH g AS ({g['web']}) SELECT DISTINCT a.s FROM g a JOIN g b ON a.o = b.s AND b.p = 'parent' JOIN g c ON b.o = c.s AND c.p = 'parent' WHERE a.p = 'on_host' AND c.o = 'host:com' AND regexp_matches(a.o, '{_HOSTS}')",
        "rpq_node_filter_pairs": _pairs("web", "0 parent 1, 1 parent 1", "1", f"SELECT DISTINCT e.s, reach.node AS o FROM g e JOIN reach ON reach.origin = e.o AND reach.q = 1 WHERE e.p = 'on_host' AND regexp_matches(e.o, '{_HOSTS}') --"),
        "rpq_meet_must_pass": "SELECT n::INTEGER AS nation, EXISTS (SELECT 1 FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_nationkey = n AND n_regionkey = r) AS found FROM (VALUES (2, 0), (3, 1), (19, 3)) t(n, r)",
        "rpq_set_to_constant": _pairs("web", "0 on_host 1, 1 parent 1", "1", "SELECT DISTINCT origin AS s", s="page:5", where="AND node IN ('host:com', 'host:org', 'host:net')"),
        "rpq_sql_subquery": "SELECT DISTINCT 'customer:' || c_custkey AS s, 'region:' || n_regionkey AS o FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_regionkey = (SELECT n_regionkey FROM nation WHERE n_nationkey = 3)",
        "rpq_pattern_same_variable": f"WITH g AS ({g['flow']}) SELECT DISTINCT a.s AS x, v.o AS y FROM g a JOIN g b ON a.o = b.s AND b.o = a.s JOIN g v ON v.s = a.s AND v.p = 'view' WHERE a.p = 'error' AND b.p = 'click'",
        "rpq_unknown_self": "SELECT 'host:nowhere' AS o",
        "rpq_limited": _pairs("web", "0 on_host 1, 1 parent 1", "1", "SELECT least(25, count(*)) AS n FROM (SELECT DISTINCT origin, node", where=")"),
        "rpq_next_by_ranges": _pairs("web", "0 on_host 1, 1 parent 1", "1", "SELECT min(origin) AS value", where="AND node = 'host:com' AND origin >= 'page:5'"),
        "graph_labels_into": f"SELECT p, count(*) AS edges, count(DISTINCT o) AS targets FROM ({g['web']}) WHERE o >= 'host:a' AND o <= 'host:n' GROUP BY p",
        "graph_sources_of": f"SELECT count(DISTINCT s) AS sources FROM ({g['web']}) WHERE p IN ('parent', 'on_host')",
        "rpq_must_pass": "SELECT DISTINCT 'order:' || o_orderkey AS s, 'region:' || n_regionkey AS o FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE n_nationkey = 3",
        "rpq_negated": oracle.recursion("pulse", "0 click_1 0", "0", None, "user:7", "SELECT DISTINCT a.s FROM g a JOIN g b ON a.o = b.s AND b.p = 'click_1' JOIN reach ON reach.node = b.o WHERE a.p NOT IN ('error_3', 'click_1')"),
        "rpq_same_variable": f"WITH g AS ({g['flow']}) SELECT DISTINCT a.s FROM g a JOIN g b ON a.o = b.s AND b.o = a.s WHERE a.p = 'error' AND b.p = 'click'",
        "rpq_rare_auto": _pairs("pulse", "0 error_3 1, 1 error_3 1, 1 signup_2 2, 2 click_1 3, 3 click_1 3", "3"),
        "rpq_rare_split": _pairs("web", "0 on_host 1, 1 parent 2, 2 parent 2", "2"),
        "rpq_next_solution": _pairs("web", "0 on_host 1, 1 parent 1", "1", "SELECT min(origin) AS value", where="AND node = 'host:com' AND origin >= 'page:5'"),
        "rpq_pattern_join": f"""WITH g AS ({g['trade']}), based AS (SELECT s, o FROM g WHERE p = 'based_in'),
            ends AS (SELECT s, o AS r FROM based UNION SELECT b.s, x.o FROM based b JOIN g x ON x.s = b.o AND x.p = 'in_region')
            SELECT DISTINCT l.s AS c, pl.s AS o, su.o AS s, ends.r FROM g l JOIN g pl ON pl.o = l.s AND pl.p = 'placed_by' JOIN g h ON h.s = pl.s AND h.p = 'has_part' JOIN g su ON su.s = h.o AND su.p = 'supplied_by' JOIN ends ON ends.s = su.o WHERE l.p = 'lives_in' AND l.o = 'nation:3'""",
        "rpq_sql": "SELECT 'customer:' || o_custkey AS customer, 1::BIGINT AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN part ON l_partkey = p_partkey WHERE p_brand = 'Brand#17' GROUP BY o_custkey",
        "rpq_local_function": f"WITH g AS ({g['chat']}) SELECT DISTINCT a.s, b.o FROM g a JOIN g b ON a.o = b.s WHERE a.p = 'user' AND b.p = 'assistant'",
        "rpq_accepts_function": words_sql("clicks"),
        "fast_single": "SELECT 'order:' || o_orderkey AS s, 'customer:' || o_custkey AS o FROM orders",
        "fast_alternation": "SELECT 'customer:' || c_custkey AS s, 'nation:' || c_nationkey AS o FROM customer UNION SELECT 'nation:' || s_nationkey, 'supplier:' || s_suppkey FROM supplier",
        "fast_concat": oracle.of("w08"),
        "base_semi_naive": parent,
        "base_squaring": parent,
        "base_joins": "SELECT 'customer:' || c AS s, count(*) AS paths, count(DISTINCT p) AS parts FROM (SELECT DISTINCT o_custkey AS c, o_orderkey AS k, l_partkey AS p FROM orders JOIN lineitem ON o_orderkey = l_orderkey) GROUP BY c",
        "index_columns": f"SELECT col, pos::BIGINT AS pos, symbol::BIGINT AS symbol, rank::BIGINT AS rank, start::BIGINT AS start FROM (VALUES {rows}) t(col, pos, symbol, rank, start)",
        "index_triples": f"SELECT s, p, o FROM ({g['chat']})",
        "index_backward": f"SELECT o, p, count(*) AS n FROM ({g['web']}) GROUP BY o, p",
        "encode_edges": f"SELECT s, p, o FROM ({g['chat']})",
        "complete_edges": f"WITH g AS ({g['chat']}) SELECT s, p, o FROM g UNION ALL SELECT o, '^' || p, s FROM g",
        "graph_stats": f"WITH g AS ({g['trade']}) SELECT count(*) AS edges, (SELECT count(*) FROM (SELECT s FROM g UNION SELECT o FROM g)) AS nodes, count(DISTINCT s) AS subjects, count(DISTINCT p) AS labels, count(DISTINCT o) AS objects FROM g",
        "graph_label_counts": f"SELECT p, count(*) AS n FROM ({g['trade']}) GROUP BY p",
        "graph_selectivity": f"SELECT p, count(*) AS edges, count(DISTINCT s) AS sources, count(DISTINCT o) AS targets FROM ({g['trade']}) GROUP BY p",
        "index_interval": f"WITH g AS ({g['web']}) SELECT 'objects' AS what, count(*) AS n FROM g WHERE o >= 'host:a' AND o <= 'host:n' UNION ALL SELECT 'labels', count(*) FROM g WHERE p >= 'in_lang' AND p <= 'on_host'",
        "wavelet_ranks": f"""WITH g AS ({g['chat']}), nodes AS (SELECT n, row_number() OVER (ORDER BY n) - 1 AS id FROM (SELECT s AS n FROM g UNION SELECT o FROM g)),
            labels AS (SELECT p, row_number() OVER (ORDER BY p) AS id FROM (SELECT DISTINCT p FROM g)), e AS (SELECT a.id AS s, labels.id AS p, b.id AS o FROM g JOIN nodes a ON a.n = g.s JOIN nodes b ON b.n = g.o JOIN labels USING (p)),
            full_e AS (SELECT s, p, o FROM e UNION ALL SELECT o, p + (SELECT count(*) FROM labels), s FROM e), h AS (SELECT length(bin((SELECT count(*) FROM nodes) - 1)) AS h),
            seq AS (SELECT row_number() OVER (ORDER BY p, o, s) AS pos, s AS symbol FROM full_e), levels AS (SELECT unnest(range(0, h))::INTEGER AS level, h FROM h),
            bits AS (SELECT level, row_number() OVER (PARTITION BY level ORDER BY symbol >> (h - level), pos) AS n, (symbol >> (h - level - 1)) & 1 AS bit FROM seq, levels)
            SELECT level, n AS i, ones::BIGINT AS ones FROM (SELECT level, n, sum(bit) OVER (PARTITION BY level ORDER BY n) AS ones FROM bits) WHERE n % 5 = 0 AND n < (SELECT count(*) FROM seq) UNION ALL SELECT level, 0, 0 FROM levels""",
        "measure_space": f"""WITH g AS ({g['trade']}), k AS (SELECT count(*) AS n, count(DISTINCT s) AS s, count(DISTINCT p) AS p, count(DISTINCT o) AS o, (SELECT count(*) FROM (SELECT s FROM g UNION SELECT o FROM g)) AS v FROM g),
            b AS (SELECT *, greatest(1, ceil(log2(greatest(2, 2 * p)))) AS bp, greatest(1, ceil(log2(greatest(2, v)))) AS bv, greatest(1, ceil(log2(greatest(2, s)))) + greatest(1, ceil(log2(greatest(2, p)))) + greatest(1, ceil(log2(greatest(2, o)))) AS packed FROM k)
            SELECT component, round(bytes / n, 6) AS bytes_per_edge FROM (SELECT n, unnest(['L_p', 'L_s', 'C_o', 'C_p', 'visited masks', 'label masks', 'plain triples', 'packed triples']) AS component,
                unnest([2 * n * bp * 1.125 / 8, 2 * n * bv * 1.125 / 8, 8.0 * (v + 1), 8.0 * (2 * p + 1), 4.0 * v, 8.0 * p, 12.0 * n, n * packed / 8]::DOUBLE[]) AS bytes FROM b)""",
        "measure_counters": f"""WITH RECURSIVE g AS ({g['web']}), hosts(h, d) AS (SELECT 'host:com', 0 UNION ALL SELECT g.s, d + 1 FROM g JOIN hosts ON g.o = hosts.h AND g.p = 'parent'),
            pages AS (SELECT g.s, d + 1 AS d FROM g JOIN hosts ON g.o = hosts.h AND g.p = 'on_host')
            SELECT (SELECT count(DISTINCT d) FROM (SELECT d FROM hosts UNION SELECT d FROM pages)) AS rounds, (SELECT count(*) FROM hosts) + (SELECT count(*) FROM pages) AS visits, 2 * (SELECT count(*) FROM hosts) + (SELECT count(*) FROM pages) AS states, 2::BIGINT AS labels_read, (SELECT count(*) FROM pages) AS answers""",
        "measure_ring": f"""WITH RECURSIVE g AS ({g['web']}), hosts(h) AS (SELECT 'host:com' UNION ALL SELECT g.s FROM g JOIN hosts ON g.o = hosts.h AND g.p = 'parent')
            SELECT (SELECT count(*) FROM hosts) - 1 + n AS subjects, n AS answers FROM (SELECT count(*) AS n FROM g JOIN hosts ON g.o = hosts.h AND g.p = 'on_host')""",
        "measure_winners": "SELECT 20::BIGINT AS patterns, 1.0::DOUBLE AS share, 20::BIGINT AS queries, 2::BIGINT AS methods, 0::BIGINT AS timeouts, 1::BIGINT AS answers_a_query",
        "log_patterns": "SELECT pattern, count(*) AS n FROM events JOIN (VALUES " + ", ".join(f"('{t}', '{q[3]}')" for t, q in ASKED.items()) + ") t(kind, pattern) ON event_type = kind GROUP BY pattern",
        "log_clean": f"WITH n AS (SELECT s AS n FROM ({g['web']}) UNION SELECT o FROM ({g['web']})) SELECT NULL::VARCHAR AS s, 'parent*' AS path, n AS o FROM n WHERE n = 'host:example.com' UNION ALL SELECT n, 'on_host/parent*', NULL FROM n WHERE n = 'page:0'",
        "log_answers": " UNION ALL ".join(oracle.model(q.id, x, kind, n) for x, kind, q, n in log.models()),
        "stream_matches": "SELECT user_id, event_id FROM (SELECT *, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events) WHERE event_type = 'purchase' AND before = 'click'",
        "measure_product": oracle.recursion("pulse", "0 error_3 1, 1 error_3 1", "1", None, "user:7", "SELECT count(*) AS product_nodes FROM reach"),
        "stream_windows": "SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2",
        "stream_sessions": "SELECT user_id, count(*) FILTER (WHERE fresh) AS sessions, count(*) AS events FROM (SELECT user_id, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 6 HOUR, true) AS fresh FROM events) GROUP BY user_id",
        "stream_purchases": "SELECT c.user_id, c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'",
        "stream_deduplicated": "SELECT DISTINCT event_id FROM events",
        "stream_labelled": "SELECT event_id, user_id, CASE event_type WHEN 'click' THEN 1 ELSE 2 END AS id FROM events WHERE event_type IN ('click', 'purchase')",
        "rpq_near": _pairs("knn", "0 near_3 1, 1 near_3 2, 2 near_3 2", "2"),
        "rpq_same_text": _pairs("docs", "0 same_text 1, 1 same_text 1, 1 quality 2", "2"),
    }
    out |= {f"automaton_{n}": words_sql(n) for n in WORDS}
    return out | {n: e[1] for n, e in ENTRIES.items()}
