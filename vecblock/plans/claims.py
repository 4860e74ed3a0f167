"""What the experiments have to show whatever their timings are: (check, violations) per experiment, all zero."""

from __future__ import annotations

from pyspark.sql import functions as F

from vecblock.functions import metrics as M
from vecblock.operators import cache, exact, graph, ingest, measures, partition, search, seeding, tree, view
from vecblock.operators.search import SearchParams
from vecblock.plans import planner, vector_queries as VQ, workloads as W
from vecblock.plans.vector_queries import PARAMS, _tree, zeros
from vecblock.sources import vectors as V
from vecblock.sources.stored import fresh_path, stored

QUERIES: dict = {}
SQL: dict[str, str] = {}


def claim(*checks: str):
    """Register a function that returns one count of violations per check."""

    def put(f):
        def run(spark, sf_dir):
            got = f(spark, sf_dir)
            return spark.createDataFrame([(c, int(n)) for c, n in zip(checks, got, strict=True)], "check string, violations long")

        QUERIES[f.__name__] = run
        SQL[f.__name__] = zeros(*checks)
        return f

    return put


def _rows(name: str, spark, sf_dir) -> list:
    return (W.QUERIES.get(name) or VQ.QUERIES[name])(spark, sf_dir).collect()


def bad(rows, rule) -> int:
    return sum(not rule(r) for r in rows) + (not rows)


@claim("tree_at_full_width_is_exact", "some_width_of_each_method_reaches_the_target")
def memory_curves_hold(spark, d):
    rows = _rows("w_memory_curves", spark, d)
    widest = {}
    for r in rows:
        widest[r.input, r.method, r.k] = max(widest.get((r.input, r.method, r.k), 0), r.recall)
    leaves = {r.input: max(x.width for x in rows if x.input == r.input and x.method == "tree") for r in rows}
    full = [r for r in rows if r.method == "tree" and r.width == leaves[r.input]]
    return bad(full, lambda r: r.recall == 1.0), sum(v < W.TARGET for (_, m, k), v in widest.items() if k == 10 and m in ("tree", "tree_links", "layered"))


@claim("every_method_reaches_the_target", "every_method_has_hops")
def hops_hold(spark, d):
    rows = [r for r in _rows("w_hops", spark, d) if r.method in ("tree_1_links", "tree_2_links", "layered")]
    return bad(rows, lambda r: r.recall >= W.TARGET), bad(rows, lambda r: r.mean_hops > 0)


@claim("every_method_reaches_the_target", "leaves_on_disk_in_tree_order_are_closer_than_at_random", "the_tree_reads_fewer_places_than_the_graphs")
def cpu_proxies_hold(spark, d):
    rows = {r.method: r for r in _rows("w_cpu_proxies", spark, d)}
    graphs = [r for m, r in rows.items() if not m.startswith("tree_dfs") and not m.startswith("tree_random")]
    return bad(list(rows.values()), lambda r: r.recall >= W.TARGET), rows["tree_dfs"].mean_gap > rows["tree_random"].mean_gap, sum(rows["tree_dfs"].reads_per_query > r.reads_per_query for r in graphs)


@claim("both_methods_are_traced", "the_tree_takes_fewer_steps")
def step_trace_holds(spark, d):
    rows = _rows("w_step_trace", spark, d)
    steps = {m: sum(r.method == m for r in rows) for m in ("tree", "layered")}
    return min(steps.values()) == 0, steps["tree"] > steps["layered"]


@claim("recall_near_the_target")
def batch_holds(spark, d):
    return (bad(_rows("w_batch", spark, d), lambda r: r.recall >= 0.9),)


@claim("recall_reaches_the_target", "large_batches_are_not_slower_than_single_queries")
def batch_served_holds(spark, d):
    rows = _rows("w_batch_served", spark, d)
    qps = {r.batch: r.qps for r in rows}
    return bad(rows, lambda r: r.recall >= W.TARGET), qps[max(qps)] < 0.5 * qps[min(qps)]


@claim("answers_of_a_version_stay", "versions_were_committed", "the_last_version_answers_otherwise")
def async_holds(spark, d):
    rows = _rows("w_async", spark, d)
    return bad(rows[:-1], lambda r: r.answers_changed == 0), rows[-1].newest_version < 2, rows[-1].answers_changed


@claim("resident_within_capacity", "half_full_start_reads_no_more")
def lru_holds(spark, d):
    rows = _rows("w_lru", spark, d)
    read = {(r.capacity_bytes, r.start): r.bytes_read for r in rows}
    return bad(rows, lambda r: r.resident_bytes <= r.capacity_bytes), sum(read[c, "half"] > read[c, "zero"] for c, _ in read)


@claim("cached_answers_differ")
def cached_search_equal(spark, d):
    """A cache of three leaves' size gives the answers of the search in Spark."""
    v = V.hubs(spark, d)
    q, t = stored(V.queries_of(v, 20), "q"), _tree(spark, d, "hubs")
    p = SearchParams(beam=2)
    held = cache.LeafCache(t, 3 * PARAMS.leaf_capacity * (8 * t.dim + 8))
    a, b = (stored(VQ.long_rank(x), "found") for x in (held.rows(held.search(q, p)), search.search(t, q, p)))
    return (a.exceptAll(b).count() + b.exceptAll(a).count() + (held.peak > held.max_bytes),)


@claim("recall_is_one")
def metrics_hold(spark, d):
    return (bad(_rows("w_metrics", spark, d), lambda r: r.recall == 1.0),)


@claim("exact_search_is_exact", "full_width_is_exact")
def farthest_holds(spark, d):
    rows = _rows("w_farthest", spark, d)
    rows = [r for r in rows if r.method.startswith("tree_")]
    leaves = {r.input: max(x.width for x in rows if x.input == r.input) for r in rows}
    return bad([r for r in rows if r.method == "tree_exact"], lambda r: r.recall == 1.0), bad([r for r in rows if r.width == leaves[r.input]], lambda r: r.recall == 1.0)


@claim("double_is_exact", "half_precision_keeps_recall")
def low_precision_holds(spark, d):
    got = {r.stored: r.recall for r in _rows("w_low_precision", spark, d)}
    return got["double"] < 1, got["float16"] < 0.98


@claim("search_grows_slower_than_the_collection", "height_grows_by_logarithm")
def scale_holds(spark, d):
    rows = sorted(_rows("w_scale", spark, d), key=lambda r: r.n)
    a, b = rows[0], rows[-1]
    return b.distances_per_query / a.distances_per_query > 0.25 * b.n / a.n, b.height > a.height + 6


@claim("correlated_order_reads_no_more")
def temporal_holds(spark, d):
    last = {}
    for r in _rows("w_temporal", spark, d):
        last[r.input, r.order] = max(last.get((r.input, r.order), 0), r.cum_reads)
    return (sum(last[i, "correlated"] > last[i, "random"] for i in ("raw", "hubs")),)


@claim("no_view_has_full_recall", "correlated_queries_keep_views_longer")
def view_survival_holds(spark, d):
    rows = _rows("w_view_survival", spark, d)
    served = {(r.input, r.view_size, r.order): r.mean_served for r in rows}
    return bad([r for r in rows if r.view_size == 0], lambda r: r.recall == 1.0), sum(served["hubs", s, "correlated"] < served["hubs", s, "random"] for s in (20, 50, 100))


@claim("one_view_per_renewal", "radius_and_probe_keep_recall")
def view_triggers_hold(spark, d):
    rows = {r.trigger: r for r in _rows("w_view_triggers", spark, d)}
    return sum(r.views < 1 for r in rows.values()), sum(rows[x].recall < 0.3 for x in ("radius", "probe"))


@claim("all_rows_are_accounted_for", "old_rows_stay_in_their_old_leaf_or_its_parts")
def growth_holds(spark, d):
    rows = _rows("w_growth", spark, d)
    parents = {}
    for r in rows:
        if r.old_leaf is not None:
            parents.setdefault(r.new_leaf, set()).add(r.old_leaf)
    return sum(r.n for r in rows) != V.hubs(spark, d).count(), sum(len(x) > 1 for x in parents.values())


@claim("recall_grows_with_the_beam", "more_is_read_with_it")
def beam_curve_holds(spark, d):
    rows = sorted(_rows("beam_curve", spark, d), key=lambda r: (r.input, r.beam))
    pairs = [(a, b) for a, b in zip(rows, rows[1:]) if a.input == b.input]
    return sum(b.recall < a.recall - 1e-9 for a, b in pairs), sum(b.share_read < a.share_read for a, b in pairs)


@claim("links_do_not_lower_recall")
def ablation_leaves_hold(spark, d):
    rows = {r.link_leaves: r.recall for r in _rows("w_ablation_leaves", spark, d)}
    return (sum(v < rows[0] - 1e-9 for v in rows.values()),)


@claim("recall_grows_with_the_beam", "wide_beam_reaches_the_target")
def disk_holds(spark, d):
    rows = _rows("w_disk", spark, d)
    by = {}
    for r in rows:
        by.setdefault(r.n, []).append((r.beam, r.recall))
    return sum(sorted(x)[0][1] > sorted(x)[-1][1] for x in by.values()), sum(sorted(x)[-1][1] < W.TARGET for x in by.values())


@claim("shares_sum_to_one")
def build_time_holds(spark, d):
    rows = _rows("w_build_time", spark, d)
    return (abs(sum(r.share for r in rows if r.method == "block_tree") - 1) > 1e-9,)


@claim("wide_searches_reach_the_target")
def baselines_hold(spark, d):
    """Only the widest search of each method is judged, so the narrow ones are left to their own queries."""
    found = W.baselines(spark, d, ("layered_recall", "layered_recall_sharded", "disk_graph_recall", "tree_rng_recall"), [max(W.WIDTHS)])
    return (bad(found, lambda r: r[2] >= W.TARGET),)


@claim("quantised_search_with_rescoring", "hashing")
def controls_hold(spark, d):
    return max(r.recall for r in _rows("quantised_recall", spark, d)) < 0.9, _rows("lsh_recall", spark, d)[0].recall < 0.5


@claim("eight_distinct_seeds", "seeds_by_passes", "clusters_of_every_control_hold_all_rows")
def seeds_hold(spark, d):
    v = V.vectors(spark, d)
    got = seeding.d2(v, 8).collect()
    n = v.count()
    ml = _rows("mllib_partitions", spark, d)
    return len({r.vec_id for r in got}) != 8, seeding.parallel(v, 8).count() != 8, sum(sum(r.n for r in ml if r.method == m) != n for m in ("kmeans", "bisecting"))


@claim("flat_parts", "binary_parts", "sizes", "balance")
def hierarchies_hold(spark, d):
    n = V.vectors(spark, d).count()
    flat = _rows("hierarchy_flat", spark, d)
    sizes = _rows("hierarchy_sizes", spark, d)
    binary = _rows("hierarchy_binary", spark, d)
    fill = _rows("tree_balance", spark, d)[0]
    return sum(r.n for r in flat if r.level == 1) != n, sum(r.most > PARAMS.partition.max_cluster_rows for r in binary), sum(r.n for r in sizes if r.is_final) != n, fill.fill_max > PARAMS.leaf_capacity or fill.children_max > PARAMS.inner_capacity


@claim("rounds_do_not_raise_it", "counted_by_hand")
def inertia_falls(spark, d):
    """Squared error within clusters over Lloyd rounds."""
    v = V.vectors(spark, d)
    start = v.where("vec_id < 6").select(F.col("vec_id").cast("int").alias("pos"), "v")
    errors = [partition.inertia(v, start), *[partition.inertia(v, partition.kmeans(v, start, k)) for k in (1, 3)]]
    pairs = v.join(F.broadcast(start.select(F.col("v").alias("c"))), how="cross")  # six centers
    plain = pairs.groupBy("vec_id").agg(F.min(M.l2_sq(F.col("v"), F.col("c"))).alias("e")).agg(F.sum("e")).first()[0]
    return sum(b > a + 1e-9 for a, b in zip(errors, errors[1:])), abs(plain - errors[0]) > 1e-6


@claim("mean_squared_distance_to_the_mean_is_the_dimension")
def mahalanobis_holds(spark, d):
    """Full Mahalanobis distance: by definition the squares sum to (n - 1) times the dimension."""
    v = V.vectors(spark, d)
    white = stored(v.select("vec_id", M.whiten(F.col("v"), M.fit_whitener(v)).alias("v"), F.lit(0).alias("one")), "white")
    mean = M.centroid(white, ["one"]).select(F.col("v").alias("m"))
    got = white.join(F.broadcast(mean), how="cross").agg(F.sum(M.l2_sq(F.col("v"), F.col("m"))).alias("s"), F.count("*").alias("n"), F.max(F.size("v")).alias("k")).first()  # one mean
    return (abs(got.s / ((got.n - 1) * got.k) - 1) > 1e-6,)


@claim("walks_find_no_worse_answers", "a_wider_list_finds_no_worse")
def walks_hold(spark, d):
    v, t = V.hubs(spark, d), _tree(spark, d, "hubs")
    q = V.queries_of(v)
    truth, links = stored(exact.knn(v, q, 10), "truth"), stored(graph.build_links(t, 8, 4), "links")
    recall = lambda f: float(measures.recall(f, truth, 10).first().recall)
    plain = stored(search.search(t, q, SearchParams(beam=2)), "seeds")
    branch = VQ.QUERIES["greedy_per_branch"](spark, d)
    wide = [recall(graph.greedy(plain, links, v, q, 10, ef=w)) for w in (10, 40)]
    return recall(branch) < recall(plain) - 1e-9, wide[1] < wide[0] - 1e-9


@claim("links_read_back", "search_with_them")
def links_saved(spark, d):
    t = _tree(spark, d, "hubs")
    links = stored(graph.build_links(t, 8, 4), "links").drop("kind")
    path = fresh_path(spark, "index")
    tree.save(t, path, links=links)
    back = tree.open_links(spark, path).select(links.columns)
    q, p = V.queries_of(V.hubs(spark, d)), SearchParams(beam=1)
    a, b = (VQ.long_rank(search.search(x, q, p, y)) for x, y in ((t, links), (tree.open_tree(spark, path), back)))
    return links.exceptAll(back).count() + back.exceptAll(links).count(), a.exceptAll(b).count() + b.exceptAll(a).count()


@claim("answers_do_not_depend_on_the_batch")
def batches_with_links_equal(spark, d):
    t, q = _tree(spark, d, "hubs"), V.queries_of(V.hubs(spark, d))
    links = stored(graph.build_links(t, 8, 4), "links")
    one, many = (stored(search.search(t, q, SearchParams(beam=1, batch_size=b), links), "found") for b in (1, 256))
    return (one.exceptAll(many).count() + many.exceptAll(one).count(),)


@claim("untouched_leaves_stay", "rows", "sound")
def insert_is_local(spark, d):
    """A few rows near one hub rewrite a few leaves; all checks of a sound tree hold."""
    v = V.hubs(spark, d)
    t = tree.build(v.where("vec_id % 50 <> 7 OR label <> 3"), PARAMS)
    grown = ingest.insert(t, v.where("vec_id % 50 = 7 AND label = 3"))
    changed = ingest.changed_leaves(t, grown).count()
    return changed > t.levels[-1] // 2, grown.rows.count() != v.count(), tree.invariants(grown).agg(F.sum("violations")).first()[0]


@claim("sums_of_leaves", "shape")
def refreshed_centroids(spark, d):
    """Sums, centroids and radii computed anew from the rows equal those that the build kept."""
    t = _tree(spark, d)
    a, b = t.nodes.alias("a"), tree.refresh_centroids(t).nodes.alias("b")
    both = a.join(b, F.col("a.node_id") == F.col("b.node_id"))
    far = both.where((M.l2(F.col("a.centroid"), F.col("b.centroid")) > 1e-9) | (F.abs(F.col("a.radius") - F.col("b.radius")) > 1e-6) | (F.col("a.n_rows") != F.col("b.n_rows")))
    return far.count(), abs(both.count() - t.nodes.count())


@claim("inner_fill", "sound")
def split_below_capacity(spark, d):
    """Inner nodes that split at half their capacity stay below it."""
    t = tree.build(V.hubs(spark, d), tree.TreeParams(**{**PARAMS.__dict__, "split_at": 0.5}))
    return t.nodes.where(f"NOT is_leaf AND n_children > {PARAMS.inner_capacity // 2}").count(), tree.invariants(t).agg(F.sum("violations")).first()[0]


@claim("each_layout_answers_alike")
def layouts_hold(spark, d):
    v = V.hubs(spark, d)
    q = V.queries_of(v)
    found = [stored(search.search(tree.build(v, tree.TreeParams(**{**PARAMS.__dict__, "order": o})), q, SearchParams(beam=2)), "found") for o in ("dfs", "bfs", "random")]
    return (sum(found[0].exceptAll(f).count() for f in found[1:]),)


@claim("described", "old_versions_go", "plans_are_formatted", "observed_rows")
def administration(spark, d):
    t = _tree(spark, d)
    path = fresh_path(spark, "index")
    tree.save(t, path)
    tree.save(ingest.delete(t, V.vectors(spark, d).where("vec_id < 5")), path)
    gone = tree.vacuum(spark, path, keep=1)
    described = tree.describe(tree.open_tree(spark, path))
    df, seen = planner.observed(V.vectors(spark, d))
    df.write.format("noop").mode("overwrite").save()
    n = V.vectors(spark, d).count()
    return described["n"] != n - 5 or described["version"] != 1, gone != [0] or tree.versions(spark, path) != [1], "Scan parquet" not in planner.explain(V.vectors(spark, d)), seen.get["n"] != n


@claim("choices")
def planner_holds(spark, d):
    got = {r.case: r.way for r in _rows("planner_choices", spark, d)}
    return (sum(got[k] != v for k, v in {"small": "scan", "no_tree": "scan", "large": "tree", "large_links": "tree_links", "wide_beam": "scan"}.items()),)


@claim("views_of_exact_rows", "with_links_and_a_beam")
def view_answers_hold(spark, d):
    """A view with its sub-tree and links serves queries near its anchor."""
    v, t = V.hubs(spark, d), _tree(spark, d, "hubs")
    q = V.queries_of(v).where("query_id = 0")
    w = view.create(t, q, 100)
    full = [r.vec_id for r in view.search_view(w, q, 10).orderBy("rank").collect()]
    part = [r.vec_id for r in view.search_view(w, q, 10, beam=1).orderBy("rank").collect()]
    true = [r.vec_id for r in exact.knn(v, q, 10).orderBy("rank").collect()]
    return full != true, len(set(part) & set(true)) < 8


@claim("top_ten_of_everything")
def outliers_hold(spark, d):
    rows = _rows("w_outliers", spark, d)
    return (sum(sum(r.kind == k for r in rows) != 20 for k in ("customer", "document")),)


@claim("unlike_parts_are_farther_in_the_whole")
def farthest_in_view_holds(spark, d):
    rows = _rows("w_farthest_in_view", spark, d)
    worst = {s: max(r.dist for r in rows if r.scope == s) for s in ("view", "all")}
    return (worst["view"] > worst["all"],)


@claim("two_components_per_row")
def growth_picture_holds(spark, d):
    return (abs(len(_rows("w_growth_picture", spark, d)) - V.hubs(spark, d).count()),)


@claim("estimates_within_five_percent")
def sketches_hold(spark, d):
    from vecblock.plans import relational_queries as RQ

    got = {r.event_type: r for r in RQ.QUERIES["agg_sketches"](spark, d).collect()}
    true = {r.event_type: r.users for r in RQ.QUERIES["agg_distinct"](spark, d).collect()}
    return (sum(abs(got[k].approx - v) > 0.15 * v or abs(got[k].hll - v) > 0.05 * v + 1 for k, v in true.items()),)


@claim("chebyshev", "l1", "minkowski")
def exact_in_other_metrics(spark, d):
    """Pruned exact search in trees of other norms, nearest and farthest, against all rows."""
    v = V.vectors(spark, d)
    q = stored(V.queries_of(v, 20), "q")
    out = []
    for metric in ("chebyshev", "l1", "minkowski"):
        t = tree.with_metric(_tree(spark, d), metric)
        wrong = 0
        for far in (False, True):
            a, b = (stored(VQ.long_rank(x), "found") for x in (search.search_exact(t, q, 10, farthest=far), exact.knn(v, q, 10, metric, farthest=far)))
            wrong += a.exceptAll(b).count() + b.exceptAll(a).count()
        out.append(wrong)
    return out


@claim("grid_equals_broadcast")
def blocks_of_queries_equal(spark, d):
    """A query set beyond the broadcast bound meets the rows on a grid of blocks."""
    v = V.vectors(spark, d)
    q = V.queries_of(v)
    want = stored(exact.knn(v, q, 10), "truth")
    bound, exact.QUERY_BLOCK = exact.QUERY_BLOCK, 64 << 10
    try:
        got = stored(exact.knn(v, q, 10), "found")
    finally:
        exact.QUERY_BLOCK = bound
    return (want.exceptAll(got).count() + got.exceptAll(want).count(),)

