"""What the schemes are compared with."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from enctopics.operators import centres, index, kestimate, relate
from enctopics.operators.vectors import matrix
from enctopics.session import kept


def fixed_k(postings: DataFrame, k: int = 10) -> DataFrame:
    """The most widespread tokens as k centres, others by number of shared documents."""
    c = centres.by_document_count(index.token_stats(postings), k)
    return relate.distribute(relate.cooccurrence(postings, c), c, postings, score="co")


def prior_encrypted(postings: DataFrame, k: int | None = None) -> DataFrame:
    """The estimated k and its centres, others by number of shared documents."""
    k = k or kestimate.estimate_k(postings).first()["k"]
    c = kept(centres.choose(postings, k, kestimate.separation(postings)))
    return relate.distribute(relate.cooccurrence(postings, c), c, postings, score="co")


def _features(vecs: DataFrame) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    return vecs.select("tok", array_to_vector(F.transform("vec", lambda x: x.cast("double"))).alias("features"))


#: Cells of a matrix of distances that a task holds.
CELLS = 1 << 21


def _nearest(x: np.ndarray, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nearest of the centres to each row, the first of equals, and the squared distance."""
    norms, width = (centres * centres).sum(axis=1), max(1, CELLS // len(centres))
    at, far = np.zeros(len(x), np.int64), np.zeros(len(x))
    for i in range(0, len(x), width):
        part = x[i : i + width]
        d = norms - 2 * (part @ centres.T)
        at[i : i + width] = k = d.argmin(axis=1)
        far[i : i + width] = np.maximum(d[np.arange(len(part)), k] + (part * part).sum(axis=1), 0)
    return at, far


def _each(rows: DataFrame, centres: np.ndarray, value: Callable[[pa.RecordBatch, np.ndarray, np.ndarray], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """value of each batch (tok, vec), and where its rows' nearest centres are and how far."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield value(batch, *_nearest(matrix(batch.column("vec")), centres))

    return rows.mapInArrow(run, schema)


def _spread(weights: np.ndarray, points: np.ndarray, k: int, seed: int) -> np.ndarray:
    """k of weighted points, each drawn by weight times squared distance to those drawn before."""
    draw = np.random.default_rng(seed)
    norms, far, out = (points * points).sum(axis=1), None, []
    for _ in range(min(k, len(points))):
        chance = np.cumsum(weights if far is None else weights * far)
        if chance[-1] <= 0:
            break
        i = min(int(np.searchsorted(chance, draw.random() * chance[-1], "right")), len(points) - 1)
        out.append(i)
        d = np.maximum(norms - 2 * (points @ points[i]) + norms[i], 0)
        d[i] = 0
        far = d if far is None else np.minimum(far, d)
    return points[out]


def vector_kmeans(vecs: DataFrame, k: int, init: str = "k-means||", seed: int = 1, rounds: int = 20, tol: float = 1e-4) -> DataFrame:
    """tok, cluster_id by k-means on vectors; init `random` is the classic form with arbitrary first centres.

    Distances are products of blocks of rows and the centres, so thousands of centres are no loop over pairs. Only centres, and
    the few candidates for them, are on the driver. Rows without a vector have no row. At most k clusters, fewer if fewer rows differ.
    """
    rows = kept(vecs.where("vec IS NOT NULL").select("tok", F.transform("vec", lambda x: x.cast("double")).alias("vec")))
    chance = lambda i: F.pmod(F.xxhash64("tok", F.lit(seed), F.lit(i)), F.lit(1 << 30)) / (1 << 30)
    first = matrix(rows.orderBy(chance(0), "tok").limit(max(1, k) if init == "random" else 1).select("vec").toArrow()["vec"])
    if not len(first):
        return rows.select("tok", F.lit(0).alias("cluster_id"))
    centres = first
    if init != "random":
        far = lambda c: _each(rows, c, lambda b, at, d: pa.record_batch([b.column("tok"), b.column("vec"), pa.array(at), pa.array(d)], ["tok", "vec", "at", "d"]), "tok string, vec array<double>, at long, d double")
        for i in (1, 2):
            found = kept(far(centres))
            cost = found.agg(F.sum("d")).first()[0]
            drawn = found.where(chance(i) * F.lit(cost) < 2 * k * F.col("d")).orderBy("tok").select("vec").toArrow()["vec"]
            centres = np.concatenate([centres, matrix(drawn)]) if len(drawn) else centres
        centres = np.unique(centres, axis=0)
        if len(centres) > k:
            weights = np.zeros(len(centres))
            for r in far(centres).groupBy("at").count().toLocalIterator():
                weights[r["at"]] = r["count"]
            centres = _spread(weights, centres, k, seed)
    cell = "at long, n double, s array<double>"

    def sums(parts: Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
        n, s = np.zeros(k), np.zeros((k, first.shape[1]))
        for at, m, x in parts:
            order = np.argsort(at, kind="stable")
            own, starts = np.unique(at[order], return_index=True)
            n[own] += np.add.reduceat(m[order], starts)
            s[own] += np.add.reduceat(x[order], starts)
        own = np.flatnonzero(n)
        yield pa.record_batch([pa.array(own), pa.array(n[own]), pa.array(list(s[own]), pa.list_(pa.float64()))], ["at", "n", "s"])

    def moved(centres: np.ndarray) -> np.ndarray:
        def partly(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            xs = (matrix(b.column("vec")) for b in batches if b.num_rows)
            yield from sums((_nearest(x, centres)[0], np.ones(len(x)), x) for x in xs)

        def wholly(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            yield from sums((b.column("at").to_numpy(), b.column("n").to_numpy(), matrix(b.column("s"))) for b in batches if b.num_rows)

        got = rows.mapInArrow(partly, cell).repartition(rows.sparkSession.sparkContext.defaultParallelism, "at").mapInArrow(wholly, cell).toArrow()
        out = centres.copy()
        out[got["at"].to_numpy()] = matrix(got["s"]) / got["n"].to_numpy()[:, None]
        return out

    for _ in range(rounds):
        before, centres = centres, moved(centres)
        if ((centres - before) ** 2).sum(axis=1).max() <= tol * tol:
            break
    return _each(rows, centres, lambda b, at, d: pa.record_batch([b.column("tok"), pa.array(at.astype(np.int32))], ["tok", "cluster_id"]), "tok string, cluster_id int")


def kmeans_cost(vecs: DataFrame, k: int, init: str = "random", seed: int = 1) -> tuple[int, float]:
    """Rounds until the centres stood still, and the cost reached."""
    from pyspark.ml.clustering import KMeans

    summary = KMeans(k=k, seed=seed, initMode=init).fit(_features(vecs)).summary
    return summary.numIter, summary.trainingCost


def hierarchical(vecs: DataFrame, k: int, branches: int = 4, seed: int = 1) -> DataFrame:
    """tok, cluster_id: a few branches by bisection, then k-means with spread first centres inside each."""
    from pyspark.ml.clustering import BisectingKMeans

    rows = _features(vecs)
    top = BisectingKMeans(k=min(branches, k), seed=seed).fit(rows).transform(rows).select("tok", F.col("prediction").alias("branch"))
    top = kept(top.join(vecs.select("tok", "vec"), "tok"))
    sizes = {r["branch"]: r["count"] for r in top.groupBy("branch").count().collect()}
    total, base, out = sum(sizes.values()), 0, None
    for branch, n in sorted(sizes.items()):
        part = top.where(F.col("branch") == branch)
        here = max(1, min(n, round(k * n / total)))
        if here > 1:
            named = vector_kmeans(part, here, seed=seed).select("tok", (F.col("cluster_id") + base).alias("cluster_id"))
        else:
            named = part.select("tok", F.lit(base).alias("cluster_id"))
        out = named if out is None else out.unionByName(named)
        base += here
    return out


def subsumption_parents(postings: DataFrame, share: float = 0.8) -> DataFrame:
    """tok, parent: the most specific token that is in at least `share` of a token's documents and is itself wider."""
    df = postings.groupBy("tok").agg(F.count("*").alias("df"))
    a = postings.select("tok", "doc_id")
    b = postings.select(F.col("tok").alias("parent"), "doc_id")
    both = a.join(b, "doc_id").where("tok <> parent").groupBy("tok", "parent").agg(F.count("*").alias("n"))
    rows = both.join(df, "tok").join(df.select(F.col("tok").alias("parent"), F.col("df").alias("dfp")), "parent")
    good = rows.where((F.col("n") >= share * F.col("df")) & (F.col("dfp") > F.col("df")))
    return good.groupBy("tok").agg(F.min(F.struct("dfp", "parent"))["parent"].alias("parent"))


def _paths(parents: DataFrame, tokens: DataFrame, depth: int) -> DataFrame:
    """tok, path: from the root down, at most depth steps."""
    p = parents.select(F.col("tok").alias("child"), "parent")
    rows = tokens.select("tok", F.array("tok").alias("path"))
    for _ in range(depth):
        up = rows.join(p, F.element_at("path", 1) == F.col("child"), "left")
        rows = up.select("tok", F.when(F.col("parent").isNull(), F.col("path")).otherwise(F.concat(F.array("parent"), F.col("path"))).alias("path"))
    return rows


def taxonomy(postings: DataFrame, k: int, depth: int = 4) -> DataFrame:
    """tok, cluster_id: medoids are the tokens with most descendants; a token goes to the medoid with the best path
    similarity, twice the depth of the last common ancestor over the sum of depths, or to cluster -1 without one."""
    paths = kept(_paths(subsumption_parents(postings), postings.select("tok").distinct(), depth))
    weight = paths.select(F.explode("path").alias("m")).groupBy("m").agg(F.count("*").alias("n"))
    order = Window.orderBy(F.desc("n"), "m")
    top = weight.orderBy(F.desc("n"), "m").limit(k).withColumn("cluster_id", F.row_number().over(order))
    medoids = kept(top.join(paths, F.col("m") == F.col("tok")).select("m", "cluster_id", F.col("path").alias("mpath")))
    steps = paths.select("tok", "path", F.posexplode("path").alias("at", "node"))
    msteps = medoids.select("cluster_id", F.size("mpath").alias("msize"), F.posexplode("mpath").alias("mat", "mnode"))
    met = steps.join(F.broadcast(msteps), (F.col("node") == F.col("mnode")) & (F.col("at") == F.col("mat")))
    sim = met.groupBy("tok", "cluster_id").agg((2 * (F.max("at") + 1) / (F.max(F.size("path")) + F.max("msize"))).alias("sim"))
    best = sim.groupBy("tok").agg(F.max_by("cluster_id", F.struct(F.round("sim", 9), -F.col("cluster_id"))).alias("cluster_id"))
    return paths.select("tok").join(best, "tok", "left").select("tok", F.coalesce("cluster_id", F.lit(-1)).alias("cluster_id"))
