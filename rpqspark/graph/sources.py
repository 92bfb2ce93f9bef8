"""Graphs of the given tables. Every graph is a table of distinct (s, p, o)."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .model import Graph


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _edges(df: DataFrame, s, p, o) -> DataFrame:
    return df.select(s.alias("s"), (F.lit(p) if isinstance(p, str) else p).alias("p"), o.alias("o"))


def _node(kind: str, key: str):
    return F.concat(F.lit(f"{kind}:"), F.col(key).cast("string"))


def _union(parts: list[DataFrame]) -> Graph:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return Graph(out.dropna().distinct())


def trade(spark: SparkSession, sf_dir: str) -> Graph:
    t = lambda n: table(spark, sf_dir, n)
    item = t("lineitem")
    return _union([
        _edges(t("customer"), _node("customer", "c_custkey"), "lives_in", _node("nation", "c_nationkey")),
        _edges(t("nation"), _node("nation", "n_nationkey"), "in_region", _node("region", "n_regionkey")),
        _edges(t("supplier"), _node("supplier", "s_suppkey"), "based_in", _node("nation", "s_nationkey")),
        _edges(t("orders"), _node("order", "o_orderkey"), "placed_by", _node("customer", "o_custkey")),
        _edges(item, _node("order", "l_orderkey"), "has_part", _node("part", "l_partkey")),
        _edges(item, _node("part", "l_partkey"), "supplied_by", _node("supplier", "l_suppkey")),
        _edges(t("part"), _node("part", "p_partkey"), "of_brand", _node("brand", "p_brand")),
    ])


def followed(events: DataFrame) -> DataFrame:
    """Each event with the user of the next event in (ts, event_id) order, over all days.

    A day is a window of its own; the last event of a day is tied to the first event
    of the next day that has any, so no window spans the table. Days are few.
    """
    e = events.select("event_id", "ts", "user_id", "event_type", "props", F.to_date("ts").alias("day"))
    inside = e.withColumn("next", F.lead("user_id").over(Window.partitionBy("day").orderBy("ts", "event_id")))
    firsts = e.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"))
    firsts = firsts.withColumn("upcoming", F.lead("first").over(Window.orderBy("day"))).select("day", "upcoming")
    return inside.join(F.broadcast(firsts), "day").withColumn("next", F.coalesce("next", "upcoming")).drop("upcoming", "day")


def flow(spark: SparkSession, sf_dir: str) -> Graph:
    e = followed(table(spark, sf_dir, "events")).filter("next IS NOT NULL")
    return _union([_edges(e, _node("user", "user_id"), F.col("event_type"), _node("user", "next"))])


def pulse(spark: SparkSession, sf_dir: str) -> Graph:
    e = followed(table(spark, sf_dir, "events")).filter("next IS NOT NULL")
    tenth = F.floor(F.get_json_object("props", "$.k").cast("int") / 10).cast("string")
    return _union([_edges(e, _node("user", "user_id"), F.concat_ws("_", "event_type", tenth), _node("user", "next"))])


HOST = "https?://([^/]+)"


def web(spark: SparkSession, sf_dir: str) -> Graph:
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html", F.regexp_extract("url", HOST, 1).alias("host"))
    hosts = pages.select("host").distinct()
    parts = F.split("host", r"\.")
    ups = hosts.select(F.explode(F.transform(F.sequence(F.lit(1), F.greatest(F.size(parts), F.lit(1))), lambda i: F.array_join(F.slice(parts, i, F.size(parts)), "."))).alias("host")).filter("host LIKE '%.%'")
    lang = F.regexp_extract("url", r"https?://[^/]+/([a-z]{2})/", 1)
    links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'<a href="/([^"]*)"'), F.lit(1))).alias("term"))
    return _union([
        _edges(pages, _node("page", "page_id"), "on_host", _node("host", "host")),
        _edges(ups.withColumn("up", F.expr("substring(host, locate('.', host) + 1)")), _node("host", "host"), "parent", _node("host", "up")),
        _edges(pages.withColumn("lang", lang).filter("lang <> ''"), _node("page", "page_id"), "in_lang", _node("lang", "lang")),
        _edges(links, _node("page", "page_id"), "links_to", _node("term", "term")),
    ])


def chat(spark: SparkSession, sf_dir: str) -> Graph:
    c = table(spark, sf_dir, "conversations")
    c = c.withColumn("next", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))).filter("next IS NOT NULL")
    name = lambda k: F.concat(F.lit("turn:"), F.col("conv_id").cast("string"), F.lit("."), F.col(k).cast("string"))
    return _union([_edges(c, name("turn"), F.col("role"), name("next"))])


def succ(spark: SparkSession, sf_dir: str) -> Graph:
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    i = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_returnflag", F.lead("l_partkey").over(w).alias("next")).filter("next IS NOT NULL")
    return _union([_edges(i, _node("part", "l_partkey"), F.col("l_returnflag"), _node("part", "next"))])


def docs(spark: SparkSession, sf_dir: str) -> Graph:
    d = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", F.xxhash64("text").alias("h"), F.length("text").alias("n"))
    same = d.withColumn("next", F.lead("doc_id").over(Window.partitionBy("h", "n").orderBy("doc_id"))).filter("next IS NOT NULL")
    return _union([
        _edges(d, _node("doc", "doc_id"), "in_lang", _node("lang", "lang")),
        _edges(d, _node("doc", "doc_id"), "from_source", _node("source", "source")),
        _edges(same, _node("doc", "doc_id"), "same_text", _node("doc", "next")),
        _edges(table(spark, sf_dir, "labels"), _node("doc", "doc_id"), "quality", _node("quality", "quality")),
    ])


#: Vectors of a packed block, and rows of one that are ranked at once.
KNN_BLOCK, KNN_ROWS = 1024, 64
#: Stands for a null label, whose vector is still near others.
NO_LABEL = -(1 << 63)


def _vector_blocks(rows: DataFrame) -> DataFrame:
    """(dim, first, ids, labels, vectors): packed unit vectors of one length, up to ``KNN_BLOCK`` in a block."""
    import numpy as np
    import pyarrow as pa

    schema = pa.schema([("dim", pa.int32()), ("first", pa.int64()), ("ids", pa.binary()), ("labels", pa.binary()), ("vectors", pa.binary())])

    def packed(have):
        x = np.array([v for _, _, v in have], float)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        ids, labels = (np.array(c, np.int64).tobytes() for c in zip(*[(i, label) for i, label, _ in have]))
        return pa.RecordBatch.from_pylist([{"dim": x.shape[1], "first": have[0][0], "ids": ids, "labels": labels, "vectors": x.tobytes()}], schema=schema)

    def work(batches):
        have: dict[int, list] = {}
        for b in batches:
            for i, v, label in zip(*(c.to_pylist() for c in b.columns)):
                part = have.setdefault(len(v), [])
                part.append((i, label, v))
                if len(part) == KNN_BLOCK:
                    yield packed(have.pop(len(v)))
        for part in have.values():
            yield packed(part)

    return rows.mapInArrow(work, "dim int, first long, ids binary, labels binary, vectors binary")


def _best(found, k: int):
    """Of arrays (a, label, b, cosine), the k rows of each a with the largest cosine, ties to the smaller b."""
    import numpy as np

    a, label, b, cosine = found
    order = np.lexsort((label, b, -cosine, a))
    starts = np.flatnonzero(np.diff(a[order], prepend=a[order][:1] - 1))
    rank = np.arange(len(a)) - np.repeat(starts, np.diff(np.append(starts, len(a))))
    return [x[order[rank < k]] for x in found]


def nearest(table: DataFrame, k: int) -> DataFrame:
    """(a, label, b): the k nearest of each vector by cosine, ties to the smaller id.

    Blocks of vectors meet in a square of groups, so that each is copied once for a row or
    column of it; a task keeps k rows a vector. Vectors without a cosine take no part.
    """
    import numpy as np
    import pyarrow as pa

    spark = table.sparkSession
    side = math.isqrt(int(spark.conf.get("spark.sql.shuffle.partitions")) - 1) + 1
    rows = table.select("vec_id", F.col("embedding").cast("array<double>").alias("v"), F.coalesce(F.col("label").cast("long"), F.lit(NO_LABEL)).alias("label")).dropna()
    rows = rows.filter(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0))
    blocks = _vector_blocks(rows)
    group = F.pmod(F.xxhash64("first", "dim"), F.lit(side))
    every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(side - 1).cast("long")))
    asked = blocks.select("dim", group.alias("i"), every.alias("j"), F.col("ids").alias("q_ids"), F.col("labels").alias("q_labels"), F.col("vectors").alias("q_vectors"))
    met = blocks.select("dim", group.alias("j"), every.alias("i"), "ids", "vectors").join(asked, ["dim", "i", "j"]).select("dim", "ids", "vectors", "q_ids", "q_labels", "q_vectors")
    schema = pa.schema([("a", pa.int64()), ("label", pa.int64()), ("b", pa.int64()), ("cosine", pa.float64())])

    def work(batches):
        found, n = [], 0
        for batch in batches:
            for dim, *packed in zip(*batch.columns):
                ids, x, q_ids, q_labels, q = (np.frombuffer(c.as_buffer(), float if i in (1, 4) else np.int64) for i, c in enumerate(packed))
                x, q = x.reshape(-1, dim.as_py()), q.reshape(-1, dim.as_py())
                for at in range(0, len(q), KNN_ROWS):
                    own, part = q_ids[at : at + KNN_ROWS], q[at : at + KNN_ROWS]
                    cosine = part @ x.T
                    cosine[own[:, None] == ids] = -np.inf
                    # Products of blocks may round equal vectors differently: what is near the k-th is taken again.
                    least = np.partition(cosine, max(0, len(ids) - k), axis=1)[:, max(0, len(ids) - k)]
                    r, c = np.nonzero((cosine >= least[:, None] - 1e-9) & (cosine > -np.inf))
                    found.append(_best([own[r], q_labels[at : at + KNN_ROWS][r], ids[c], (part[r] * x[c]).sum(axis=1)], k))
                    n += len(found[-1][0])
                if n > 1_000_000:
                    found = [_best([np.concatenate(f) for f in zip(*found)], k)]
                    n = 0
        if found:
            best = _best([np.concatenate(f) for f in zip(*found)], k)
            for at in range(0, len(best[0]), 10_000):
                yield pa.RecordBatch.from_arrays([pa.array(x[at : at + 10_000]) for x in best], schema=schema)

    ranked = met.mapInArrow(work, "a long, label long, b long, cosine double").withColumn("k", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("cosine"), "b")))
    return ranked.filter(F.col("k") <= k).select("a", F.nullif("label", F.lit(NO_LABEL)).alias("label"), "b")


def knn(spark: SparkSession, sf_dir: str, k: int = 5) -> Graph:
    """Each vector and its k nearest by cosine, ties to the smaller id."""
    near = nearest(table(spark, sf_dir, "embeddings"), k)
    return _union([_edges(near, _node("vec", "a"), F.concat(F.lit("near_"), F.col("label").cast("string")), _node("vec", "b"))])


# The edges of the worked example.
METRO = [("UCh", "l1", "Baq"), ("LH", "l1", "UCh"), ("SA", "l2", "LH"), ("BA", "l5", "Baq"), ("BA", "l5", "SA"), ("SA", "bus", "UCh"), ("BA", "bus", "SA"), ("UCh", "bus", "BA")]


def metro(spark: SparkSession, sf_dir: str | None = None) -> Graph:
    """The worked example; its lines run both ways, buses one way."""
    both = [(o, p, s) for s, p, o in METRO if p != "bus"]
    return Graph(spark.createDataFrame(METRO + both, "s string, p string, o string"))


GRAPHS = {"trade": trade, "flow": flow, "pulse": pulse, "web": web, "chat": chat, "succ": succ, "docs": docs, "knn": knn, "metro": metro}


_stored: dict[tuple, tuple[Graph, str]] = {}


def load(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """A graph of the given tables. It is built and written once per application, as an index
    would be; later calls read what was written, as long as it is there."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key in _stored:
        g, path = _stored[key]
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        if p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p):
            return g
    g = GRAPHS[name](spark, sf_dir).stored(name)
    _stored[key] = (g, g.edges.inputFiles()[0] if g.counts() else "/")
    return g
