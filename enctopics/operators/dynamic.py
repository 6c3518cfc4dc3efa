"""Growing corpora: when to cluster anew, and how to place new tokens when not."""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from enctopics.functions.statistics import chi_square_critical
from enctopics.operators import index, relate, vectors
from enctopics.session import kept


@dataclass(frozen=True)
class Decision:
    statistic: float
    critical: float
    recluster: bool


def statistic(new: Column, existing: Column, cells: str = "single", unit: float | None = None) -> Column:
    """Chi-square of token counts: one cell against the existing count, or two cells against their mean; with a unit,
    both counts are scaled so that the existing one is the unit."""
    if unit is not None:
        return F.lit(unit) * (1 - new / existing) * (1 - new / existing)
    gap = (new - existing) * (new - existing)
    return gap / existing if cells == "single" else gap / (new + existing)


def decide(new: int, existing: int, cells: str = "single", unit: float | None = None, alpha: float = 0.05, one_sided: bool = True) -> Decision:
    """Keep the clusters only if the statistic is beyond the critical value, which means far fewer new tokens."""
    critical = chi_square_critical(1, alpha)
    if existing == 0:
        return Decision(0.0, critical, True)
    if unit is not None:
        stat = unit * (1 - new / existing) ** 2
    else:
        stat = (new - existing) ** 2 / (existing if cells == "single" else new + existing)
    return Decision(stat, critical, stat <= critical or (one_sided and new >= existing))


def accumulate(log: DataFrame) -> DataFrame:
    """batch_id, accumulated: new tokens since the last re-clustering, the batch's own included. A log has a row a batch."""
    order = Window.orderBy("batch_id")
    closed = F.coalesce(F.sum(F.col("recluster").cast("int")).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rows = log.withColumn("period", closed)
    run = Window.partitionBy("period").orderBy("batch_id").rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("accumulated", F.sum("new").over(run)).drop("period")


def abstract_coherency(abstracts: DataFrame, sims: DataFrame) -> DataFrame:
    """cluster_id, coherency: mean similarity over unordered pairs; pairs without a similarity have 0, single tokens no row."""
    size = abstracts.groupBy("cluster_id").agg(F.count("*").alias("p")).where("p > 1")
    a = abstracts.select("cluster_id", F.col("tok").alias("a"))
    b = abstracts.select("cluster_id", F.col("tok").alias("b"))
    pairs = a.join(b, "cluster_id").where("a < b").join(sims, ["a", "b"]).groupBy("cluster_id").agg(F.sum("sim").alias("sum"))
    return size.join(pairs, "cluster_id", "left").select("cluster_id", (F.coalesce("sum", F.lit(0.0)) / (F.col("p") * (F.col("p") - 1) / 2)).alias("coherency"))


def threshold(coherencies: DataFrame) -> DataFrame:
    return coherencies.agg(F.min("coherency").alias("theta"))


def best_existing(new: DataFrame, abstracts: DataFrame, sims: DataFrame, theta: float) -> DataFrame:
    """tok, cluster_id, sim: the most similar abstract of each new token, if it is beyond theta.

    A token's similarity to an abstract is that to its nearest token; sims has a = new token, b = abstract token.
    """
    both = sims.join(abstracts.select("cluster_id", F.col("tok").alias("b")), "b").join(new.select(F.col("tok").alias("a")), "a", "left_semi")
    near = both.groupBy("a", "cluster_id").agg(F.max("sim").alias("sim"))
    best = near.groupBy("a").agg(F.max_by("cluster_id", F.struct(F.round("sim", 9), -F.col("cluster_id"))).alias("cluster_id"), F.max("sim").alias("sim"))
    return best.where(F.col("sim") > theta).select(F.col("a").alias("tok"), "cluster_id", "sim")


class Sparse:
    """Vectors by place: which vectors aren't zero there, and their values. A product costs what the two have in common."""

    def __init__(self):
        self.n, self.lists, self.sums = 0, {}, np.zeros(0)

    @classmethod
    def of(cls, rows: list[tuple[np.ndarray, np.ndarray]]) -> Sparse:
        """As if the rows were added one by one."""
        out = cls()
        out.n = len(rows)
        places, values = (np.concatenate([r[i] for r in rows] or [np.zeros(0, np.int32)]) for i in (0, 1))
        ids = np.repeat(np.arange(out.n, dtype=np.int32), [len(at) for at, _ in rows])
        order = np.argsort(places, kind="stable")
        known, starts = np.unique(places[order], return_index=True)
        for place, own in zip(known.tolist(), np.split(order, starts[1:])):
            out.lists[place] = ids[own], values[own], len(own)
        return out

    def add(self, at: np.ndarray, x: np.ndarray) -> None:
        for i, v in zip(at.tolist(), x.tolist()):
            ids, values, size = self.lists.get(i) or (np.zeros(4, np.int32), np.zeros(4), 0)
            if size == len(ids):
                ids, values = np.concatenate([ids, np.zeros_like(ids)]), np.concatenate([values, np.zeros_like(values)])
            ids[size], values[size] = self.n, v
            self.lists[i] = ids, values, size + 1
        self.n += 1

    def best(self, at: np.ndarray, x: np.ndarray, digits: int | None = None, first: int | None = None) -> tuple[int, float]:
        """The earliest of the most similar vectors, of the first ones if so many are named, and its product; -1 and -2 for none."""
        n = self.n if first is None else min(first, self.n)
        if n == 0:
            return -1, -2.0
        if len(self.sums) < self.n:
            self.sums = np.zeros(2 * self.n)
        met = []
        for i, v in zip(at.tolist(), x.tolist()):
            if i in self.lists:
                ids, values, size = self.lists[i]
                size = size if n == self.n else int(np.searchsorted(ids[:size], n))
                if size:
                    self.sums[ids[:size]] += values[:size] * v
                    met.append(ids[:size])
        ids = (met[0] if len(met) == 1 else np.unique(np.concatenate(met))) if met else np.zeros(0, np.int32)
        sims = self.sums[ids]
        self.sums[ids] = 0.0
        order = sims if digits is None else np.round(sims, digits)
        k = int(order.argmax()) if len(ids) else -1
        if len(ids) < n and (k < 0 or order[k] <= 0):  # some vector has nothing in common
            apart = int(np.argmin(np.append(ids, n) == np.arange(len(ids) + 1)))
            if k < 0 or order[k] < 0 or apart < ids[k]:
                return apart, 0.0
        return int(ids[k]), float(sims[k])


def _rows(table: pa.Table | pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The places and the values of the columns at and x."""
    for batch in table.to_batches() if isinstance(table, pa.Table) else [table]:
        at, x = batch.column("at"), batch.column("x")
        ends, places, values = at.offsets.to_numpy(), at.values.to_numpy(), x.values.to_numpy()
        starts = x.offsets.to_numpy()
        for k in range(batch.num_rows):
            yield places[ends[k] : ends[k + 1]], values[starts[k] : starts[k + 1]]


def _lead(theta: float, first_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Founders in order: a token founds a cluster unless it is beyond theta to an earlier founder."""
        lead = Sparse()
        for batch in batches:
            found, ids = [], []
            for k, (at, x) in enumerate(_rows(batch)):
                if lead.best(at, x)[1] <= theta:
                    found.append(k)
                    ids.append(first_id + lead.n)
                    lead.add(at, x)
            part = batch.take(pa.array(found, pa.int64()))
            yield pa.record_batch([part.column("tok"), pa.array(ids, pa.int64()), part.column("f"), part.column("at"), part.column("x")], ["tok", "cluster_id", "f", "at", "x"])

    return run


#: Numbers of the vectors that a task holds an index of, and tokens that are compared with it in one task, about.
HELD, COMPARED = 1 << 21, 100_000


def _nearest(new: DataFrame, have: DataFrame, preceding: bool) -> DataFrame:
    """tok, own, own_sim: of have (id, tok, f, at, x) what is most similar to each new token (tok, f, at, x), then the least id; -1
    and -2 where there is none. preceding: only what comes before the token by falling f and tok, in whose order ids are.

    Both sides are dealt out, the one in blocks of what a task can hold, the other in parts, and each two meet in a task: no
    vector is on the driver, and no task holds all of them.
    """
    blocks = max(1, -(-int(have.agg(F.sum(F.size("at"))).first()[0] or 0) // HELD))
    parts = max(1, -(-new.count() // COMPARED), -(-new.sparkSession.sparkContext.defaultParallelism // blocks))
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    columns = ("block", "part", "side", "id", "tok", "f", "at", "x")
    left = have.withColumns({"block": F.pmod(F.xxhash64("id", "tok"), F.lit(blocks)).cast("int"), "side": F.lit(0)}).withColumn("part", every(parts)).select(*columns)
    right = new.withColumns({"part": F.pmod(F.xxhash64("tok"), F.lit(parts)).cast("int"), "side": F.lit(1), "id": F.lit(-1).cast("long")}).withColumn("block", every(blocks)).select(*columns)
    met = left.unionByName(right).repartition(blocks * parts, "block", "part").sortWithinPartitions("block", "part", "side", "id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, known, ids, order, base = None, [], [], [], None
        for batch in batches:
            out = []
            columns = (batch.column(c).to_pylist() for c in ("block", "part", "side", "id", "tok", "f"))
            for block, part, side, i, tok, f, (at, x) in zip(*columns, _rows(batch)):
                if (block, part) != here:
                    here, known, ids, order, base = (block, part), [], [], [], None
                if side == 0:
                    known.append((at.copy(), x.copy()))
                    ids.append(i)
                    order.append((-f, tok))
                    continue
                if base is None:
                    base, known = Sparse.of(known), []
                k, sim = base.best(at, x, 12, bisect_left(order, (-f, tok)) if preceding else None)
                out.append((tok, ids[k] if k >= 0 else -1, sim, round(sim, 12)))
            cols = list(zip(*out)) if out else [()] * 4
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, (pa.string(), pa.int64(), pa.float64(), pa.float64()))], ["tok", "own", "own_sim", "place"])

    found = met.mapInArrow(run, "tok string, own long, own_sim double, place double")
    if blocks > 1:
        found = found.groupBy("tok").agg(F.max_by(F.struct("own", "own_sim"), F.struct("place", -F.col("own"))).alias("best")).select("tok", "best.own", "best.own_sim")
    return found.select("tok", "own", "own_sim")


def attach(new: DataFrame, abstracts: DataFrame, theta: float) -> DataFrame:
    """tok, cluster_id, sim, founded for new tokens (tok, f, vec) and abstracts (cluster_id, tok, vec), by cosine; vec, or places at and values x.

    Exactly what the loop over tokens by falling f gives, in three steps: only tokens with no abstract beyond theta
    can found a cluster, so these alone are gone through in order; every other token picks the best of all abstracts
    and of the founders that precede it. Vectors are held by what isn't zero in them, as most tokens are in few documents.
    """
    new, abstracts = kept(vectors.sparse(new).select("tok", F.col("f").cast("long").alias("f"), "at", "x")), kept(vectors.sparse(abstracts))
    last = abstracts.agg(F.coalesce(F.max("cluster_id"), F.lit(-1))).first()[0]
    have = abstracts.select(F.col("cluster_id").cast("long").alias("id"), "tok", F.lit(0).cast("long").alias("f"), "at", "x")
    near = kept(_nearest(new, have, preceding=False))
    residual = new.join(near.where(F.col("own_sim") <= theta), "tok", "left_semi").select("tok", "f", "at", "x").repartition(1).sortWithinPartitions(F.desc("f"), "tok")
    found = kept(residual.mapInArrow(_lead(theta, last + 1), "tok string, cluster_id long, f long, at array<int>, x array<double>"))
    none = F.when(F.col("own_sim") > theta, F.col("own")).otherwise(-1), F.when(F.col("own_sim") > theta, F.col("own_sim")).otherwise(-2.0)
    placed = near.select("tok", none[0].alias("cluster_id"), none[1].alias("sim"))
    if found.isEmpty():
        return placed.withColumn("founded", F.lit(False))
    others = new.join(found.select("tok"), "tok", "left_anti")
    lead = _nearest(others, found.select(F.col("cluster_id").alias("id"), "tok", "f", "at", "x"), preceding=True)
    better = (F.col("own_sim") > theta) & (F.round("own_sim", 12) > F.round("sim", 12))
    both = placed.join(lead, "tok").select("tok", F.when(better, F.col("own")).otherwise(F.col("cluster_id")).alias("cluster_id"), F.when(better, F.col("own_sim")).otherwise(F.col("sim")).alias("sim"), F.lit(False).alias("founded"))
    return both.unionByName(found.select("tok", "cluster_id", F.lit(1.0).alias("sim"), F.lit(True).alias("founded")))


def alone(new: DataFrame, clusters: DataFrame, placed: DataFrame) -> DataFrame:
    """tok, cluster_id, sim, founded: one cluster, beyond all of clusters and placed, for new tokens that no vector describes."""
    last = F.coalesce(F.max("cluster_id"), F.lit(-1))
    top = clusters.select(F.col("cluster_id").cast("long").alias("cluster_id")).union(placed.select("cluster_id")).agg(last.alias("top"))
    first = new.agg(F.min("tok").alias("first"))
    return new.select("tok").crossJoin(F.broadcast(top)).crossJoin(F.broadcast(first)).select("tok", (F.col("top") + 1).alias("cluster_id"), F.lit(0.0).alias("sim"), (F.col("tok") == F.col("first")).alias("founded"))


def attach_by_relatedness(postings: DataFrame, new: DataFrame, centres: DataFrame) -> DataFrame:
    """tok, cluster_id of new tokens by relatedness to the centres over the merged postings; -1 where they meet none."""
    edges = relate.relatedness(postings, centres).join(new.select("tok"), "tok", "left_semi")
    placed = relate.distribute(edges, centres).where("NOT is_centre").select("tok", "cluster_id")
    return new.select("tok").join(placed, "tok", "left").select("tok", F.coalesce("cluster_id", F.lit(-1)).alias("cluster_id"))


def apply(clusters: DataFrame, placed: DataFrame) -> DataFrame:
    """Clusters with the new tokens in."""
    more = placed.select("tok", F.col("cluster_id").cast("int").alias("cluster_id"), F.coalesce("founded", F.lit(False)).alias("is_centre"))
    return clusters.select("tok", "cluster_id", "is_centre").unionByName(more)


def counts(temp: DataFrame, central: DataFrame, count: str = "batch") -> tuple[int, int]:
    """Tokens of a batch, all or those unseen so far, and tokens of the index."""
    new = index.new_tokens(temp, central) if count == "unseen" else temp.select("tok").distinct()
    return new.count(), central.select("tok").distinct().count()
