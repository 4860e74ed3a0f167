"""The experiments, on the given tables: each query returns the rows of one figure or table.

Timings are of this machine and run; reads, hops and distance counts are exact
and the better guide at these sizes.
"""

from __future__ import annotations

import time
from functools import lru_cache

from pyspark.sql import functions as F

from vecblock.baselines import graphs as G
from vecblock.baselines import others
from vecblock.functions import metrics as M
from vecblock.operators import cache, dissim, exact, graph, ingest, measures, search, temporal, tree, view
from vecblock.operators.partition import PartitionParams
from vecblock.operators.search import ALL, SearchParams
from vecblock.plans.vector_queries import PARAMS, _sessions, _tree
from vecblock.sources import vectors as V
from vecblock.sources.stored import fresh_path, stored

QUERIES: dict = {}
SQL: dict[str, str] = {}
SOURCES = {"raw": V.vectors, "hubs": V.hubs}


def query(f):
    """Register an experiment; one session runs it once per set of tables."""
    once = lru_cache(maxsize=2)(f)
    QUERIES[f.__name__] = once
    return once


def rows(spark, data, schema: str):
    return spark.createDataFrame(data, schema)


def _truth(v, q, k=10, far=False):
    return stored(exact.knn(v, q, k, farthest=far), "truth")


def _recall(found, truth, k=10) -> float:
    return float(measures.recall(found, truth, k).first().recall or 0.0)


#: Recall at which methods are compared.
TARGET = 0.95


def _avg(df, column: str) -> float:
    return float(df.agg(F.avg(column)).first()[0] or 0.0)


def _first_width(run, truth, widths, k=10):
    """(width, recall, answer, seconds) of the first width whose answer reaches TARGET, or of the last."""
    for w in widths:
        start = time.perf_counter()
        found = stored(run(w), "found")
        seconds = time.perf_counter() - start
        recall = _recall(found.select("query_id", "rank", "vec_id"), truth, k)
        if recall >= TARGET:
            break
    return w, recall, found, seconds


def _ranked(found, far=False):
    """The rows of a graph in one shard, merged, with the hops and vectors of each query."""
    per = found.groupBy("query_id").agg(F.max("hops").alias("hops"), F.max("n_seen").alias("n_seen"))
    return G.merged(found, 10, far).join(per, "query_id") if "rank" not in found.columns else found


BEAMS, EFS = (1, 2, 4, 8, 16, ALL), (10, 20, 50, 100, 200, 500, 1200)


def beam_curve(spark, sf_dir, beams=(1, 2, 4, 8)):
    """Recall against leaves and rows read, easy and hard input."""
    out = []
    for kind, source in SOURCES.items():
        v = source(spark, sf_dir)
        q, t = V.queries_of(v), _tree(spark, sf_dir, kind)
        truth = _truth(v, q)
        n = q.count()
        sizes = t.nodes.where("is_leaf").select("node_id", "n_rows")
        for b in beams:
            p = SearchParams(beam=b)
            log = stored(search.descend(t, q, p), "log")
            read = log.where("is_leaf").join(sizes, "node_id").agg(F.sum("n_rows")).first()[0] or 0
            out.append((kind, b, _recall(search.search(t, q, p), truth), read / max(1, n * t.n)))
    return rows(spark, out, "input string, beam int, recall double, share_read double")


@query
def w_memory_curves(spark, sf_dir):
    """Recall and throughput of every method over its own width, on all cores and in one task."""
    out = []
    for kind, source in SOURCES.items():
        v = source(spark, sf_dir)
        q = stored(V.queries_of(v), "q")
        n = q.count()
        t = _tree(spark, sf_dir, kind)
        links = stored(graph.build_links(t, 8, 4), "links")
        graphs = {name: G.build(v, name, degree=8, ef_build=32, width=32) for name in ("layered", "disk_graph", "tree_rng")}
        for k in (10, 100):
            truth = _truth(v, q, k)
            for threads, asked in (("all", q), ("one", q.coalesce(1))):
                for beam in (1, 2, 4, 8, 16, ALL) if threads == "all" else (4,):
                    for name, ln in (("tree", None), ("tree_links", links)):
                        start = time.perf_counter()
                        found = stored(search.search(t, asked, SearchParams(k=k, beam=beam), ln), "found")
                        out.append((kind, name, threads, min(beam, t.levels[-1]), k, _recall(found, truth, k), n / (time.perf_counter() - start)))
            for name, g in graphs.items():
                for ef in (k, 50, 200, 1200) if k == 10 else (k, 200):
                    start = time.perf_counter()
                    found = stored(G.merged(G.search(g, q, k, ef), k), "found")
                    out.append((kind, name, "one", ef, k, _recall(found, truth, k), n / (time.perf_counter() - start)))
    return rows(spark, out, "input string, method string, threads string, width int, k int, recall double, qps double")


@query
def w_build_time(spark, sf_dir):
    """Seconds per phase; the links' share."""
    out = []
    v = stored(V.hubs(spark, sf_dir), "v")
    start = time.perf_counter()
    t = tree.build(v, PARAMS)
    mid = time.perf_counter()
    measures.timed(graph.build_links(t, 16, 8))
    end = time.perf_counter()
    out += [("block_tree", "tree", mid - start, (mid - start) / (end - start)), ("block_tree", "links", end - mid, (end - mid) / (end - start))]
    for name in ("layered", "disk_graph", "tree_rng"):
        start = time.perf_counter()
        G.build(v, name, degree=16, ef_build=64, width=64)
        out.append((name, "build", time.perf_counter() - start, 1.0))
    return rows(spark, out, "method string, phase string, seconds double, share double")


@query
def w_cpu_proxies(spark, sf_dir):
    """Stand-ins for hardware counters at the width where each method reaches the target recall.

    A read is a leaf of the tree or a vector of a graph; a gap is the distance on disk between consecutive
    reads, in leaves or rows; a graph's rows lie in the order of their ids.
    """
    out = []
    v = stored(V.hubs(spark, sf_dir), "v")
    q = stored(V.queries_of(v), "q")
    n, truth, t = q.count(), _truth(v, q), _tree(spark, sf_dir, "hubs")
    beam, recall, _, seconds = _first_width(lambda b: search.search(t, q, SearchParams(beam=b)), truth, BEAMS)
    log = stored(search.descend(t, q, SearchParams(beam=beam)).where("is_leaf"), "log")
    for order in ("dfs", "random"):
        rank = F.col("node_order") if order == "dfs" else F.row_number().over(search.Window.orderBy(F.md5(F.col("node_id").cast("string"))))
        place = t.nodes.where("is_leaf").select("node_id", "n_rows", F.row_number().over(search.Window.orderBy(rank)).alias("node_order"))
        placed = log.join(place, "node_id").withColumn("seq", F.row_number().over(search.Window.orderBy("query_id", "node_order")))
        gap = measures.seek_distance(placed).first()
        per = placed.agg((F.count("*") / n).alias("r"), (F.sum("n_rows") * t.dim * 8 / n).alias("b")).first()
        out.append((f"tree_{order}", min(beam, t.levels[-1]), recall, float(per.r), float(per.b), float(gap.mean_gap or 0), float(gap.sequential or 0), n / seconds))
    for name in ("layered", "disk_graph", "tree_rng"):
        g = G.build(v, name, degree=8, ef_build=32, width=32)
        ef, recall, found, seconds = _first_width(lambda w, g=g: _ranked(G.search(g, q, 10, w)), truth, EFS)
        steps = G.trace(g, q, 10, ef).withColumn("node_order", F.col("vec_id")).withColumn("seq", F.row_number().over(search.Window.orderBy("query_id", "shard", "step")))
        gap = measures.seek_distance(steps).first()
        seen = _avg(found.select("query_id", "n_seen").distinct(), "n_seen")
        out.append((name, ef, recall, seen, seen * t.dim * 8, float(gap.mean_gap or 0), float(gap.sequential or 0), n / seconds))
    return rows(spark, out, "method string, width int, recall double, reads_per_query double, bytes_per_query double, mean_gap double, sequential double, qps double")


@query
def w_disk(spark, sf_dir):
    """An index read from its files, nothing cached: recall, milliseconds and megabytes per query, for two sizes."""
    out = []
    for times in (4, 16):
        v = stored(V.rolled(V.hubs(spark, sf_dir), times), "v")
        t = tree.build(v, PARAMS)
        path = fresh_path(spark, "index")
        tree.save(t, path)
        opened = tree.open_tree(spark, path)
        q = stored(V.queries_of(v, 20), "q")
        n, truth = q.count(), _truth(v, q)
        for beam in (1, 4, 16):
            start = time.perf_counter()
            found = stored(search.search(opened, q, SearchParams(beam=beam)), "found")
            ms = measures.latency_ms(n, time.perf_counter() - start)
            read = search.descend(opened, q, SearchParams(beam=beam)).where("is_leaf").join(opened.nodes.select("node_id", "n_rows"), "node_id").agg(F.sum("n_rows")).first()[0]
            out.append((t.n, beam, _recall(found, truth), ms, read * (8 * t.dim + 8) / n / 1e6))
    return rows(spark, out, "n long, beam int, recall double, ms_per_query double, mb_per_query double")


def _leaf_log(spark, sf_dir, order: str, kind: str = "hubs", beam: int = 2):
    v, s = _sessions(spark, sf_dir, SOURCES[kind], order)
    log = search.descend(_tree(spark, sf_dir, kind), s.select("query_id", "v"), SearchParams(beam=beam)).where("is_leaf").join(s.select("query_id", "seq"), "query_id")
    w = search.Window.orderBy("seq", "node_id")
    return stored(log.select("query_id", "node_id", (F.row_number().over(w) - 1).cast("long").alias("seq")), "log")


@query
def w_lru(spark, sf_dir):
    """Hit rate, resident bytes and bytes read as queries go on, served through a bounded cache of leaves that starts empty or half full."""
    _, s = _sessions(spark, sf_dir)
    s = stored(s, "s")
    t = _tree(spark, sf_dir, "hubs")
    whole = t.n * (8 * t.dim + 8)
    out = None
    for share in (0.25, 0.5):
        for start, preload in (("zero", 0.0), ("half", 0.5)):
            held = cache.LeafCache(t, int(whole * share), preload)
            held.search(s, SearchParams(beam=2, batch_size=16), order="seq")
            part = held.accesses().groupBy(F.floor(F.col("seq") / 25).cast("long").alias("bucket")).agg(F.avg(F.col("hit").cast("double")).alias("hit_rate"), F.max("resident").alias("resident"), F.max("resident_bytes").alias("resident_bytes"))
            part = part.select(F.lit(held.max_bytes).alias("capacity_bytes"), F.lit(start).alias("start"), "bucket", "hit_rate", "resident", "resident_bytes", F.lit(held.peak).alias("peak_bytes"), F.lit(held.bytes_read).alias("bytes_read"))
            out = part if out is None else out.union(part)
    return out


@query
def w_hops(spark, sf_dir):
    """Rows whose links are read (and, in the tree, nodes opened) until the target recall, by degree."""
    v = stored(V.hubs(spark, sf_dir), "v")
    q, t = stored(V.queries_of(v), "q"), _tree(spark, sf_dir, "hubs")
    truth = _truth(v, q)
    nodes = {b: _avg(search.descend(t, q, SearchParams(beam=b)).groupBy("query_id").agg(F.count("*").alias("n")), "n") for b in (1, 2)}
    out = []
    for degree in (4, 8, 16, 32):
        links = stored(graph.build_links(t, degree, 4), "links")
        for beam in (1, 2):
            seeds = stored(search.search(t, q, SearchParams(beam=beam)), "seeds")
            ef, recall, got, _ = _first_width(lambda w, seeds=seeds, links=links: graph.greedy(seeds, links, v, q, 10, ef=w), truth, EFS)
            out.append((degree, f"tree_{beam}_links", ef, recall, nodes[beam] + _avg(got.select("query_id", "hops").distinct(), "hops")))
        single = graph.random_seeds(q, v)
        ef, recall, got, _ = _first_width(lambda w, links=links: graph.greedy(single, links, v, q, 10, ef=w), truth, EFS)
        out.append((degree, "links_one_random_seed", ef, recall, _avg(got.select("query_id", "hops").distinct(), "hops")))
        # without the relaxed pruning rule (alpha 1) a flat graph is a plain pruned neighbourhood graph
        for name, kind, alpha in (("layered", "layered", 1.0), ("disk_graph", "disk_graph", 1.2), ("flat_graph_alpha_1", "disk_graph", 1.0)):
            if kind != "layered" and degree != 8:
                continue
            g = G.build(v, kind, degree=degree, ef_build=32, width=32, alpha=alpha)
            ef, recall, got, _ = _first_width(lambda w, g=g: _ranked(G.search(g, q, 10, w)), truth, EFS)
            out.append((degree, name, ef, recall, _avg(got.select("query_id", "hops").distinct(), "hops")))
    return rows(spark, out, "degree int, method string, width int, recall double, mean_hops double")


@query
def w_step_trace(spark, sf_dir):
    """Steps of one query in the tree (nodes opened) and in the layered graph (rows expanded), at the target recall of all queries."""
    v = stored(V.hubs(spark, sf_dir), "v")
    every, t = stored(V.queries_of(v, 20), "q"), _tree(spark, sf_dir, "hubs")
    truth, q = _truth(v, every), V.queries_of(v).where("query_id = 10")
    beam, _, _, _ = _first_width(lambda b: search.search(t, every, SearchParams(beam=b)), truth, BEAMS)
    tree_steps = search.descend(t, q, SearchParams(beam=beam)).select(F.lit("tree").alias("method"), (F.row_number().over(search.Window.orderBy("step")) - 1).cast("long").alias("step"), "node_id")
    g = G.build(v, "layered", degree=8, ef_build=64)
    ef, _, _, _ = _first_width(lambda w: _ranked(G.search(g, every, 10, w)), truth, EFS)
    step = (F.row_number().over(search.Window.orderBy("shard", "step")) - 1).cast("long")  # one walk after the other
    return tree_steps.union(G.trace(g, q, 10, ef).select(F.lit("layered"), step, "vec_id"))


@query
def w_temporal(spark, sf_dir):
    """Cumulative leaf reads with a bounded cache: correlated and random order of the same queries."""
    out = None
    for kind in SOURCES:
        for order in ("correlated", "random"):
            part = measures.io_curve(_leaf_log(spark, sf_dir, order, kind), 10).select(F.lit(kind).alias("input"), F.lit(order).alias("order"), "seq", "cum_reads")
            out = part if out is None else out.union(part)
    return out


@query
def w_view_survival(spark, sf_dir):
    """Queries served per view, and recall while it serves, by size, order and input; 0 is no view."""
    out, sizes = None, (0, 20, 50, 100, 200)
    case = [(i, order, size) for i, (order, size) in enumerate((o, z) for o in ("correlated", "random") for z in sizes)]
    cases = rows(spark, case, "session_id long, order string, view_size int")
    for kind, source in SOURCES.items():
        v = stored(source(spark, sf_dir), "v")
        asked = None
        for order in ("correlated", "random"):
            some = _sessions(spark, sf_dir, lambda *_, v=v: v, order, 20)[1].drop("session_id").withColumn("order", F.lit(order))
            asked = some if asked is None else asked.union(some)
        # a session for each order and size, so that all replays run beside each other
        s = stored(asked.join(F.broadcast(cases), "order").select("session_id", "seq", "query_id", "v", "view_size"), "sessions")
        trace = stored(view.replay(v, s, 10, max(sizes), with_links=True, beam=4), "trace")
        part = view.survival(trace).groupBy("session_id").agg(F.count("*").alias("views"), F.avg("served").alias("mean_served"), F.max("served").alias("longest"))
        recall = trace.groupBy("session_id").agg(F.avg("recall").alias("recall"), F.avg(F.when(F.col("served_from") == "view", F.col("recall"))).alias("recall_served"))
        part = part.join(recall, "session_id").join(cases, "session_id")
        part = part.select(F.lit(kind).alias("input"), "order", "view_size", "views", "mean_served", "longest", "recall", "recall_served")
        out = part if out is None else out.union(part)
    return out


@query
def w_view_triggers(spark, sf_dir):
    """Renewal by the truth, by the view's reach, and by a probe of one leaf."""
    v, s = _sessions(spark, sf_dir)
    t = _tree(spark, sf_dir, "hubs")
    out = None
    for trigger in ("truth", "radius", "probe"):
        trace = view.replay(v, s, 10, 50, trigger=trigger, tree=t, with_links=True, beam=4)
        part = trace.agg(F.max("view_no").alias("views"), F.avg("recall").alias("recall")).select(F.lit(trigger).alias("trigger"), "views", "recall")
        out = part if out is None else out.union(part)
    return out


@query
def w_growth(spark, sf_dir):
    """Leaves before and after inserting the other 85 %."""
    v = V.hubs(spark, sf_dir)
    few = v.where("vec_id % 20 < 3")
    n = few.count()
    p = tree.TreeParams(leaf_capacity=max(4, n // 3), inner_capacity=8, partition=PartitionParams(max_cluster_rows=max(4, n // 4), fanout=4, lloyd_iters=5))
    a = tree.build(few, p)
    b = ingest.insert(a, v.where("vec_id % 20 >= 3"))
    leaf = lambda t: t.rows.select("vec_id", F.col("leaf_id").alias("leaf"))
    return ingest.lineage(leaf(a), leaf(b))


@query
def w_growth_picture(spark, sf_dir):
    return measures.pca2(V.hubs(spark, sf_dir))


@query
def w_async(spark, sf_dir):
    """A reader of an opened version, and a view, answer the same while a stream commits further versions of the index."""
    from vecblock.streaming import streams

    v = stored(V.hubs(spark, sf_dir).select("vec_id", "v"), "v")
    q = stored(V.queries_of(v), "q")
    index, source = fresh_path(spark, "index"), fresh_path(spark, "in")
    t = tree.build(v.where("vec_id % 2 = 0"), PARAMS)
    tree.save(t, index)
    for k in (1, 3):
        v.where(F.col("vec_id") % 4 == k).coalesce(1).write.mode("append").parquet(source)
    opened = tree.open_tree(spark, index)
    w = view.create(opened, q.limit(1), 50)
    p = SearchParams(beam=4)
    first, seen = stored(search.search(opened, q, p), "before"), stored(view.search_view(w, q, 5), "before")
    growing = streams.insert_stream(streams.file_stream(spark, source, v.schema), index, fresh_path(spark, "ck"))
    out = []
    while True:
        running = growing.isActive
        now = tree.versions(spark, index)[-1]
        differ = first.exceptAll(search.search(opened, q, p)).count() + seen.exceptAll(view.search_view(w, q, 5)).count()
        out.append((len(out), opened.version, now, running, int(differ)))
        if not running:
            break
    last = tree.open_tree(spark, index)
    out.append((len(out), last.version, last.version, False, int(first.exceptAll(search.search(last, q, p)).count() == 0)))
    return rows(spark, out, "reading int, reader_version int, newest_version int, stream_running boolean, answers_changed long")


@query
def w_batch(spark, sf_dir):
    """Throughput of whole searches by the number of queries handed over together, with and without links, at the target recall."""
    v = stored(V.hubs(spark, sf_dir), "v")
    q = stored(V.queries_of(v, 2), "q")
    ids = [r.query_id for r in q.select("query_id").orderBy("query_id").collect()]  # the stated queries
    t = _tree(spark, sf_dir, "hubs")
    truth = _truth(v, q)
    links = stored(graph.build_links(t, 16, 4), "links")
    beam, _, _, _ = _first_width(lambda b: search.search(t, q, SearchParams(beam=b)), truth, BEAMS)
    with_links, _, _, _ = _first_width(lambda b: search.search(t, q, SearchParams(beam=b), links), truth, BEAMS)
    out = []
    for size in (1, 4, 16, 64, 256):
        size = min(size, len(ids))
        asked = ids[: max(64, 4 * size) if size > 4 else 4 * size]  # a few batches of each size are timed
        for b, ln in ((beam, None), (with_links, links)):
            found, start = [], time.perf_counter()
            for a in range(0, len(asked), size):
                some = q.where(F.col("query_id").isin(asked[a : a + size]))
                found += search.search(t, some, SearchParams(beam=b, batch_size=size), ln).collect()  # k rows per query
            seconds = time.perf_counter() - start
            got = rows(spark, found, "query_id long, rank int, vec_id long, dist double")
            out.append((size, ln is not None, len(asked), _recall(got, truth.where(F.col("query_id").isin(asked))), measures.qps(len(asked), seconds)))
    return rows(spark, out, "batch int, links boolean, queries int, recall double, qps double")


@query
def w_batch_served(spark, sf_dir):
    """The same without a Spark job per batch: one process with all leaves in its cache, by the number of queries descended together."""
    v = stored(V.hubs(spark, sf_dir), "v")
    q, t = stored(V.queries_of(v, 2), "q"), _tree(spark, sf_dir, "hubs")
    truth = _truth(v, q)
    beam, _, _, _ = _first_width(lambda b: search.search(t, q, SearchParams(beam=b)), truth, BEAMS)
    held = cache.LeafCache(t, 2 * t.n * (8 * t.dim + 8), 1.0)
    out = []
    for size in (1, 4, 16, 64, 256):
        start = time.perf_counter()
        found = held.search(q, SearchParams(beam=beam, batch_size=size))
        out.append((size, _recall(held.rows(found), truth), measures.qps(q.count(), time.perf_counter() - start)))
    return rows(spark, out, "batch int, recall double, qps double")


@query
def w_farthest(spark, sf_dir):
    """Farthest-10 recall and milliseconds of the tree by beam and score, and of the dissimilarity graphs by width."""
    out = []

    def timed(kind, method, width, find, truth, n):
        start = time.perf_counter()
        found = stored(find(), "found")
        out.append((kind, method, width, _recall(found, truth), measures.latency_ms(n, time.perf_counter() - start)))

    for kind, source in {**SOURCES, "parts": V.part_vectors}.items():
        v = stored(source(spark, sf_dir), "v")
        q = stored(V.queries_of(v), "q")
        n, t = q.count(), tree.build(v, PARAMS) if kind == "parts" else _tree(spark, sf_dir, kind)
        truth = _truth(v, q, far=True)
        for beam in (1, 4, 16, ALL):
            for score in ("centroid", "bound"):
                timed(kind, f"tree_{score}", min(beam, t.levels[-1]), lambda t=t, q=q, b=beam, s=score: search.search(t, q, SearchParams(beam=b, farthest=True, node_score=s)), truth, n)
        timed(kind, "tree_exact", t.levels[-1], lambda t=t, q=q: search.search_exact(t, q, 10, farthest=True), truth, n)
        if kind == "parts":
            continue  # all pairs of parts in one task would take minutes
        for rule in ("far_lune", "far_mutual"):
            g = G.build(v, rule, degree=32)
            for ef in (10, 50):
                timed(kind, rule, ef, lambda g=g, q=q, ef=ef: G.merged(G.search(g, q, 10, ef, farthest=True), 10, True), truth, n)
    return rows(spark, out, "input string, method string, width int, recall double, ms_per_query double")


@query
def w_farthest_in_view(spark, sf_dir):
    """The unlike part of the same kind: farthest in a view of similar parts, and farthest of all."""
    v = V.part_vectors(spark, sf_dir)
    kind = V.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("vec_id"), "p_type")
    q = v.where("vec_id = 1").select(F.col("vec_id").alias("query_id"), "v")
    w = view.create(tree.build(v, PARAMS), q, 50)
    mine = kind.where("vec_id = 1").first().p_type
    both = view.search_view(w, q, 5, farthest=True).withColumn("scope", F.lit("view")).union(exact.kfn(v, q, 5).withColumn("scope", F.lit("all")))
    return both.join(kind, "vec_id").select("scope", "rank", "vec_id", "dist", (F.col("p_type") == mine).alias("same_type"))


@query
def w_ablation_leaves(spark, sf_dir):
    """Recall with links by the number of near leaves examined."""
    v = V.hubs(spark, sf_dir)
    q, t = stored(V.queries_of(v), "q"), _tree(spark, sf_dir, "hubs")
    truth = _truth(v, q)
    out = [(0, _recall(search.search(t, q, SearchParams(beam=1)), truth))]
    for s in (1, 2, 4, t.levels[-1]):
        links = stored(graph.build_links(t, 8, s), "links")
        out.append((s, _recall(search.search(t, q, SearchParams(beam=1), links), truth)))
    return rows(spark, out, "link_leaves int, recall double")


@query
def w_ablation_tree(spark, sf_dir):
    """Recall, rows read and gaps between reads at one beam by seeding, packing, capacity and disk order."""
    v = stored(V.hubs(spark, sf_dir), "v")
    q = stored(V.queries_of(v), "q")
    n, truth = q.count(), _truth(v, q)
    out = []
    grid = [(init, how, cap, "dfs") for init in ("d2", "farthest", "random") for how, cap in (("grow", 64), ("pack", 64), ("grow", 128))]
    for init, how, cap, order in [*grid, ("d2", "grow", 64, "bfs"), ("d2", "grow", 64, "random")]:
        p = tree.TreeParams(leaf_capacity=cap, inner_capacity=8, how=how, order=order, partition=PartitionParams(max_cluster_rows=40, fanout=4, lloyd_iters=5, init=init))
        t = tree.build(v, p)
        log = stored(search.descend(t, q, SearchParams(beam=2)).where("is_leaf").join(t.nodes.select("node_id", "n_rows", "node_order"), "node_id"), "log")
        gap = measures.seek_distance(log.withColumn("seq", F.row_number().over(search.Window.orderBy("query_id", "node_order")))).first()
        out.append((init, how, cap, order, t.levels[-1], _recall(search.search(t, q, SearchParams(beam=2)), truth), float(log.agg(F.sum("n_rows")).first()[0]) / n, float(gap.mean_gap or 0)))
    return rows(spark, out, "init string, how string, leaf_capacity int, layout string, leaves int, recall double, rows_read double, mean_gap double")


@query
def w_metrics(spark, sf_dir):
    """Every metric at full beam, recall one; Mahalanobis as L2 after whitening, Hamming on signs."""
    v = V.vectors(spark, sf_dir)
    sign = lambda x: (x > 0).cast("double")
    inputs = {m: (v, m) for m in ("l2", "cosine", "l1", "chebyshev", "minkowski")}
    inputs["mahalanobis"] = (stored(v.select("vec_id", M.whiten(F.col("v"), M.fit_whitener(v)).alias("v")), "white"), "l2")
    inputs["hamming"] = (stored(v.select("vec_id", F.transform("v", sign).alias("v")), "signs"), "hamming")
    out = []
    for name, (x, metric) in inputs.items():
        q = stored(V.queries_of(x, 20), "q")
        t = _tree(spark, sf_dir, "cosine") if metric == "cosine" else tree.with_metric(_tree(spark, sf_dir), metric) if x is v else tree.build(x, tree.TreeParams(**{**PARAMS.__dict__, "metric": metric}))
        out.append((name, _recall(search.search(t, q, SearchParams(beam=ALL)), exact.knn(x, q, 10, metric))))
    return rows(spark, out, "metric string, recall double")


@query
def w_scale(spark, sf_dir):
    """Height, distances per query (counted and predicted) and build seconds as the collection grows."""
    base = V.hubs(spark, sf_dir)
    q = stored(V.queries_of(base), "q")
    out = []
    for times in (1, 4, 16, 64):
        v = stored(V.rolled(base, times), "v")
        start = time.perf_counter()
        t = tree.build(v, PARAMS)
        built = time.perf_counter() - start
        log = stored(search.descend(t, q, SearchParams(beam=4)), "log")
        inner = _avg(measures.distance_count(log), "n_scored")
        read = _avg(log.where("is_leaf").join(t.nodes.select("node_id", "n_rows"), "node_id").groupBy("query_id").agg(F.sum("n_rows").alias("n")), "n")
        touched = _avg(measures.touched_fraction(log, sum(t.levels)), "touched")
        p = PARAMS
        predicted = measures.predicted_cost(spark, t.n, p.partition.fanout, p.partition.lloyd_iters, p.leaf_capacity, 4, 4, p.inner_capacity, 1).where("step = 'search'").first().distances
        out.append((t.n, t.height, inner + read, float(predicted), touched, built))
    return rows(spark, out, "n long, height int, distances_per_query double, predicted double, nodes_touched double, build_seconds double")


@query
def w_outliers(spark, sf_dir):
    """The least common customers and documents."""
    a = dissim.commonality(V.customer_vectors(spark, sf_dir)).where("commonality IS NOT NULL").withColumn("kind", F.lit("customer"))
    b = dissim.commonality(V.document_vectors(spark, sf_dir)).withColumn("kind", F.lit("document"))
    top = lambda t: t.orderBy("commonality", "vec_id").limit(20)
    return top(a).union(top(b)).select("kind", "vec_id", "commonality")


@query
def w_low_precision(spark, sf_dir):
    """Recall when leaves are stored in fewer bits."""
    v = V.hubs(spark, sf_dir)
    q = V.queries_of(v)
    t, truth = _tree(spark, sf_dir, "hubs"), _truth(v, q)
    out = []
    for kind in ("double", "float16", "int8"):
        path = fresh_path(spark, "index")
        tree.save(t, path, kind)
        out.append((kind, _recall(search.search(tree.open_tree(spark, path), q, SearchParams(beam=ALL)), truth)))
    return rows(spark, out, "stored string, recall double")


#: Kind, shards at least, and parameters of each comparison method's recall.
BASELINES = {
    "layered_recall": ("layered", 1, {"degree": 8, "ef_build": 32}),
    "layered_recall_sharded": ("layered", 4, {"degree": 8, "ef_build": 32}),
    "disk_graph_recall": ("disk_graph", 1, {"degree": 8, "width": 32}),
    "tree_rng_recall": ("tree_rng", 1, {"degree": 8}),
}
WIDTHS = (10, 50, 1000)


@lru_cache(maxsize=2)
def _asked(spark, sf_dir):
    """(vectors, every row whose id is divisible by 20, their true ten), for all comparison methods."""
    v = stored(V.hubs(spark, sf_dir), "v")
    q = stored(V.queries_of(v, 20), "q")
    return v, q, _truth(v, q)


def baselines(spark, sf_dir, names, widths=WIDTHS) -> list[tuple]:
    """(kind, width, recall); methods that come to the same shards by the same parameters are one graph."""
    v, q, truth = _asked(spark, sf_dir)
    known, out = {}, []
    for name in names:
        kind, shards, params = BASELINES[name]
        shards = G.shards_of(v, shards)
        if (key := (kind, shards, *params.items())) not in known:
            g = G.build(v, kind, shards=shards, **params)
            known[key] = [(kind, ef, _recall(G.merged(G.nearest(g, q, 10, ef), 10), truth)) for ef in widths]
        out += known[key]
    return out


def _baseline(name: str):
    def run(spark, sf_dir):
        return rows(spark, baselines(spark, sf_dir, [name]), "method string, width int, recall double")

    run.__name__ = name
    query(run)


for _name in BASELINES:
    _baseline(_name)


@query
def quantised_recall(spark, sf_dir):
    v = V.hubs(spark, sf_dir)
    q = V.queries_of(v)
    return rows(spark, [(r, _recall(others.quantised_search(v, q, 10, rescore=r), _truth(v, q))) for r in (20, 100)], "rescore int, recall double")


@query
def lsh_recall(spark, sf_dir):
    v = V.hubs(spark, sf_dir)
    q = V.queries_of(v)
    return rows(spark, [(_recall(others.lsh_search(v, q, 10), _truth(v, q)),)], "recall double")


@query
def planner_choices(spark, sf_dir):
    from vecblock.plans import planner

    t = _tree(spark, sf_dir, "hubs")
    big = tree.BlockTree(t.nodes, t.rows, t.params, [1, 1000, 1_000_000], 128, 10**9)
    cases = [("small", planner.choose(t.n, 50, t)), ("no_tree", planner.choose(10**9, 10, None)), ("large", planner.choose(10**9, 1000, big)), ("large_links", planner.choose(10**9, 1000, big, has_links=True)), ("wide_beam", planner.choose(10**9, 1000, big, beam=600_000))]
    return rows(spark, cases, "case string, way string")
