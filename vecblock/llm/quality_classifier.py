"""Quality classifier: document evidence with hierarchical empirical Bayes for sites.

A logistic model over surface features of a text gives each document a logit.
Documents are grouped by host and by path below the host; a group's rate of good
documents is its mean document probability, shrunk towards the host's rate,
itself shrunk towards the global one.  The strength of each shrinkage comes from the
spread between groups (method of moments), so sparse sites fall back to their
parents.  A document's posterior adds its path's log-odds against the global
log-odds to its own logit.

The model is fitted on at most ``sample`` labelled rows, those with the smallest
hashes of doc_id; group statistics cover every document.

Defined results: a null or blank text has all features zero and is scored like
any other; null hosts and paths are groups of their own; without labels (or with one
class only) the document's logit is the prior; rows that share a doc_id are scored
each; an empty table gives no rows; other columns pass through ``score``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType
from pyspark.sql.window import Window

from vecblock.llm import kernels as K
from vecblock.llm.logistic import Logistic
from vecblock.llm.shared import Stored, free_name

SAMPLE = 20_000
_CLASSES = [b"#*$%&<>", b"|", b"!", b"?", b"0123456789", bytes(range(65, 91)), bytes(range(97, 123)), b"\n", b".,;:", b"()[]{}=+@\"'/\\_"]
FEATURES = 5 + len(_CLASSES)
_CLASS_OF = np.full(256, len(_CLASSES), np.uint8)
for _k, _c in enumerate(_CLASSES):
    _CLASS_OF[list(_c)] = _k


def features(raw: np.ndarray, off: np.ndarray) -> np.ndarray:
    """One row per text: shares of character classes, word length, length, repetition."""
    n, size = len(off) - 1, np.diff(off)
    kinds = len(_CLASSES) + 1
    row = np.repeat(np.arange(n), size)
    share = np.bincount(row * kinds + _CLASS_OF[raw], minlength=n * kinds).reshape(n, kinds)[:, : len(_CLASSES)] / np.maximum(size, 1)[:, None]
    w = K.words(raw, off, lower=True)
    count = np.diff(w.bound)
    wrow = np.repeat(np.arange(n), count)
    chars = np.bincount(wrow, w.end - w.start, n)
    order = np.lexsort((w.hash, wrow))
    new = np.append(True, (w.hash[order][1:] != w.hash[order][:-1]) | (wrow[order][1:] != wrow[order][:-1]))[: len(order)]
    distinct = np.bincount(wrow[order], new, n)
    tri = K.window_hashes(w.hash, 3)
    trow = wrow[: len(tri)]
    ok = np.arange(len(tri)) + 3 <= w.bound[trow + 1]
    tri, trow = tri[ok], trow[ok]
    order = np.lexsort((tri, trow))
    new = np.append(True, (tri[order][1:] != tri[order][:-1]) | (trow[order][1:] != trow[order][:-1]))[: len(order)]
    kinds3, all3 = np.bincount(trow[order], new, n), np.bincount(trow, minlength=n)
    some = np.maximum(count, 1)
    extra = np.stack([chars / some, np.log1p(count), distinct / some, (all3 - kinds3) / np.maximum(all3, 1), np.log1p(size)], 1)
    return np.hstack([share, extra])


def _by_slices(batch: pa.RecordBatch, f) -> np.ndarray:
    raw, off = K.string_buffers(batch.column("text"))
    got = [f(raw[off[i] : off[j]], off[i : j + 1] - off[i]) for i, j in K.slices(off, K.SEGMENT)]
    return np.concatenate(got) if got else np.zeros((0, FEATURES))


def labelled(docs: DataFrame, labels: DataFrame, label: str, sample: int, where: Column | None = None) -> DataFrame:
    """(y, text): up to ``sample`` labelled documents, those with the smallest hashes of doc_id."""
    some = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull())
    some = some if where is None else some.where(where)
    some = some.select("doc_id", F.col(label).cast("int").alias("y")).orderBy(F.xxhash64(F.lit(5), "doc_id"), "doc_id").limit(sample)
    return docs.select("doc_id", "text").join(F.broadcast(some), "doc_id")  # at most ``sample`` ids and labels


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", sample: int = SAMPLE, where: Column | None = None) -> Logistic:
    """The model of up to ``sample`` labelled rows; ``where`` is a condition on the labels, to hold some out."""

    def run(batches):
        for batch in batches:
            x = _by_slices(batch, features)
            yield pa.RecordBatch.from_arrays([batch.column("y").cast(pa.int32()), pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), FEATURES).cast(pa.list_(pa.float64()))], names=["y", "x"])

    got = labelled(docs, labels, label, sample, where).select("y", "text").mapInArrow(run, "y int, x array<double>").toArrow()  # ``sample`` rows of FEATURES numbers
    x = np.array(got.column("x").to_pylist(), np.float64).reshape(-1, FEATURES)
    y = got.column("y").to_numpy().astype(np.float64)
    order = np.lexsort((*x.T, y))
    return Logistic(x[order], y[order])


def evidence(docs: DataFrame, model: Logistic, name: str = "logit") -> DataFrame:
    """``docs`` with the document logit."""
    schema = StructType([*docs.schema.fields, StructField(name, DoubleType())])

    def run(batches):
        for batch in batches:
            z = model.logit(_by_slices(batch, features))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(z, pa.float64())], names=[*batch.schema.names, name])

    return docs.mapInArrow(run, schema)


def _logit(p: Column) -> Column:
    return F.log(p / (1 - p))


def _strength(mean: str, n: str, over, parent: str) -> Column:
    """Pseudo-count of the parent: what the spread of group means beyond chance leaves."""
    weight = F.col(n)
    spread = F.sum(weight * F.pow(F.col(mean) - F.col(parent), 2)).over(over) / F.sum(weight).over(over)
    chance = F.sum(F.col(mean) * (1 - F.col(mean))).over(over) / F.sum(weight).over(over)
    between = F.greatest(spread - chance, F.lit(1e-6))
    within = F.col(parent) * (1 - F.col(parent))
    return F.greatest(within / between - 1, F.lit(1.0))


def site_rates(scored: DataFrame, host: str, path: str) -> DataFrame:
    """(host, path, host_rate, path_rate, global_rate) from document probabilities in ``p``."""
    spark = scored.sparkSession
    leaf = scored.groupBy(F.col(host).alias("host"), F.col(path).alias("path")).agg(F.count("*").cast("double").alias("n"), F.sum("p").alias("s"))
    leaf = Stored(spark, leaf, "sites").df
    hosts = leaf.groupBy("host").agg(F.sum("n").alias("hn"), F.sum("s").alias("hs"))
    total = hosts.agg(F.sum("hn").alias("n"), F.sum("hs").alias("s")).first()
    rate = ((total.s or 0.0) + 0.5) / ((total.n or 0.0) + 1)
    m = F.col("hs") / F.col("hn")
    spread = hosts.agg((F.sum(F.col("hn") * F.pow(m - rate, 2)) / F.sum("hn")).alias("all"), (F.sum(m * (1 - m)) / F.sum("hn")).alias("chance")).first()
    k = max(rate * (1 - rate) / max((spread["all"] or 0.0) - (spread["chance"] or 0.0), 1e-6) - 1, 1.0)
    hosts = hosts.withColumns({"global_rate": F.lit(rate), "host_rate": (F.col("hs") + k * rate) / (F.col("hn") + k)})
    both = leaf.join(hosts.withColumnRenamed("host", "h"), F.col("host").eqNullSafe(F.col("h"))).drop("h").withColumn("m", F.col("s") / F.col("n"))
    both = both.withColumn("k", _strength("m", "n", Window.partitionBy("host"), "host_rate"))
    return both.select("host", "path", "host_rate", ((F.col("s") + F.col("k") * F.col("host_rate")) / (F.col("n") + F.col("k"))).alias("path_rate"), "global_rate")


OWN = ("doc_score", "host_rate", "path_rate", "posterior", "good")


def score(docs: DataFrame, labels: DataFrame, label: str = "quality", host: str = "source", path: str = "lang", threshold: float = 0.5, sample: int = SAMPLE, model: Logistic | None = None, columns: list[str] | None = None) -> DataFrame:
    """``docs`` (or ``columns`` of it) with doc_score, host_rate, path_rate, posterior and good, which replace columns of these names.

    Texts are read once: the document logits are written with the columns that are asked for.
    """
    model = model or fit(docs, labels, label, sample)
    columns = [c for c in (docs.columns if columns is None else columns) if c.lower() not in OWN]
    logit, h, p = (free_name(docs, x) for x in ("logit_of_text", "host_of_row", "path_of_row"))
    named = docs.withColumns({h: F.col(f"`{host}`"), p: F.col(f"`{path}`")})
    full = evidence(named, model, logit).select(*[F.col(f"`{c}`") for c in columns], h, p, logit)
    full = Stored(docs.sparkSession, full, "evidence").df
    rates = site_rates(full.select(F.col(h).alias("host"), F.col(p).alias("path"), (1 / (1 + F.exp(-F.col(logit)))).alias("p")), "host", "path")
    short = {c: free_name(full, f"site_{c}") for c in rates.columns}
    rates = Stored(docs.sparkSession, rates.withColumnsRenamed(short), "rates").df  # with a known size, Spark decides on a broadcast
    full = full.join(rates, F.col(h).eqNullSafe(F.col(short["host"])) & F.col(p).eqNullSafe(F.col(short["path"])))
    z = F.col(logit) + _logit(F.col(short["path_rate"])) - _logit(F.col(short["global_rate"]))
    post = 1 / (1 + F.exp(-z))
    return full.select(*[F.col(f"`{c}`") for c in columns], (1 / (1 + F.exp(-F.col(logit)))).alias("doc_score"), F.col(short["host_rate"]).alias("host_rate"), F.col(short["path_rate"]).alias("path_rate"), post.alias("posterior"), (post >= threshold).alias("good"))


def keep_good(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The documents that the classifier does not reject, in their own columns."""
    names = docs.columns
    clash = {c: f"_own_{i}" for i, c in enumerate(names) if c.lower() in OWN}
    back = {v: k for k, v in clash.items()}
    out = score(docs.withColumnsRenamed(clash), labels, **options).where("good")
    return out.select(*[F.col(f"`{clash.get(c, c)}`").alias(c) for c in names]) if back else out.select(*[F.col(f"`{c}`") for c in names])


def host_path(url: Column) -> tuple[Column, Column]:
    """Host and first path segment of a URL column."""
    return F.regexp_extract(url, r"^[a-zA-Z]+://([^/?#]+)", 1), F.regexp_extract(url, r"^[a-zA-Z]+://[^/?#]+/([^/?#]*)", 1)


__all__ = ["evidence", "features", "fit", "host_path", "keep_good", "labelled", "score", "site_rates"]
