"""Which way to answer: exact scan, tree, tree with links, or a live view."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecblock.functions import arrays as A
from vecblock.operators import exact
from vecblock.operators import view as V
from vecblock.operators.search import SearchParams, search
from vecblock.operators.tree import BlockTree

SMALL = 5_000_000


def choose(n: int, n_queries: int, tree: BlockTree | None = None, beam: int = 4, has_links: bool = False, view: V.View | None = None, distance_to_anchor: float | None = None) -> str:
    """'view', 'tree_links', 'tree' or 'scan', by rule of cost."""
    if view is not None and distance_to_anchor is not None and distance_to_anchor <= view.radius / 2:
        return "view"
    if tree is None or not tree.levels:
        return "scan"
    read = beam * max(1, n // max(1, tree.levels[-1]))
    if n * n_queries <= SMALL or read >= n / 2:
        return "scan"
    return "tree_links" if has_links else "tree"


def topk(df: DataFrame, q: DataFrame, k: int, tree: BlockTree | None = None, links: DataFrame | None = None, view: V.View | None = None, **options) -> DataFrame:
    """The answer by the chosen way; ``options`` go to SearchParams."""
    p = SearchParams(k=k, **options)
    n, m = (tree.n if tree else df.count()), q.count()
    far = None
    if view is not None:
        first = q.first()
        far = float(A.distance(A.np.asarray(first.v, float), view.anchor, view.metric)) if first else None
    way = choose(n, m, tree, p.beam, links is not None, view, far)
    if way == "view":
        return V.search_view(view, q, k, p.farthest, exclude_self=p.exclude_self)
    if way == "scan":
        return exact.knn(df, q, k, tree.params.metric if tree else "l2", p.exclude_self, p.farthest)
    return search(tree, q, p, links if way == "tree_links" else None)


def rewrite_topk(df: DataFrame, literal: list[float], k: int, tree: BlockTree | None = None, **options) -> DataFrame:
    """ORDER BY distance(v, literal) LIMIT k as a search of one query."""
    q = df.sparkSession.createDataFrame([(-1, [float(x) for x in literal])], "query_id long, v array<double>")
    return topk(df, q, k, tree, exclude_self=False, **options).select("rank", "vec_id", "dist").orderBy("rank")


def explain(df: DataFrame) -> str:
    """The formatted physical plan as text."""
    return df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")


def observed(df: DataFrame, name: str = "rows"):
    """(df, observation): row and null counts read off while the plan runs."""
    from pyspark.sql import Observation

    o = Observation(name)
    return df.observe(o, F.count(F.lit(1)).alias("n")), o
