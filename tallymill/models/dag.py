"""Topics in a directed acyclic hierarchy. A token's latent value is a path from the root to a
leaf; counts are kept for every edge of a document and for (leaf, word), the latter sketched. sweep()
takes two levels, path_sweep() the paths of any hierarchy."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tallymill.functions.keyed import draw, uniform
from tallymill.models.lda import _spread, sketch_vectors, topic_counts
from tallymill.models.mixture import gamma
from tallymill.params import SketchParams, smoothed


def paths(spark: SparkSession, edges: list[tuple[str, str]], root: str) -> DataFrame:
    """(path, leaf, nodes) of all ways from the root to a leaf, by a recursive query."""
    spark.createDataFrame(edges, "parent string, child string").createOrReplaceTempView("dag_edges")
    return spark.sql(f"""
      WITH RECURSIVE walk(node, nodes) AS (
        SELECT '{root}', array('{root}')
        UNION ALL SELECT e.child, concat(w.nodes, array(e.child)) FROM walk w JOIN dag_edges e ON e.parent = w.node)
      SELECT CAST(row_number() OVER (ORDER BY concat_ws('/', nodes)) - 1 AS INT) AS path, node AS leaf, nodes
      FROM walk WHERE node NOT IN (SELECT parent FROM dag_edges)""")


def initial(toks: DataFrame, supers: int, subs: int, seed: int) -> DataFrame:
    """toks(doc_id, pos, v) with z = super * subs + sub from keyed uniforms."""
    u = uniform("z0", seed, 0, F.col("doc_id"), F.col("pos"))
    return toks.select("doc_id", "pos", "v", F.floor(u * (supers * subs)).cast("int").alias("z"))


def _dirichlet_rows(df: DataFrame, column: str, by: str, prior: float, seed: int, sweep: int, tag: int) -> DataFrame:
    """Arrays of counts replaced by gamma variates of count + prior, keyed by row and place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = b.column(column).to_pylist()
            if not rows:
                continue
            n, ids = np.array(rows, float), b.column(by).to_numpy()
            g = gamma((n + prior).ravel(), seed, sweep, tag, np.repeat(ids, n.shape[1]), np.tile(np.arange(n.shape[1]), len(ids)))
            yield pa.record_batch([b.column(by), pa.array(g.reshape(n.shape).tolist(), pa.list_(pa.float64()))], names=[by, column])

    return df.select(by, column).mapInArrow(run, f"{by} long, {column} array<double>")


def sweep(toks: DataFrame, supers: int, subs: int, alpha: float, gamma_prior: float, beta: float, types: int, seed: int, number: int, p: SketchParams | None = None, draws: bool = False) -> DataFrame:
    """Draws (super, sub) of every token of toks(doc_id, pos, v, z) given the distributions: smoothed
    shares, or with draws=True Dirichlet draws, of supers in a document, of subs under a super in a
    document, and of words in a sub."""
    smoothed(min(alpha, gamma_prior), beta)
    size = supers * subs
    own = _spread(toks.groupBy("doc_id", "z").agg(F.count("*").cast("double").alias("n")), "doc_id", "z", "n", size).withColumnRenamed("est", "joint")
    leaf = toks.select("doc_id", "pos", "v", F.pmod("z", F.lit(subs)).alias("z"))
    words = topic_counts(leaf, subs) if p is None else sketch_vectors(leaf, subs, p)

    def part(s: Column) -> Column:
        return F.aggregate(F.slice("joint", s * subs + 1, F.lit(subs)), F.lit(0.0), lambda a, x: a + x)

    own = own.withColumn("sup", F.transform(F.sequence(F.lit(0), F.lit(supers - 1)), part))
    if draws:
        g = _dirichlet_rows(own, "sup", "doc_id", alpha, seed, number, 1)
        h = _dirichlet_rows(own, "joint", "doc_id", gamma_prior, seed, number, 2)
        w = _dirichlet_rows(words, "est", "v", beta, seed, number, 3)
        total = w.agg(*[F.sum(F.get("est", F.lit(t))).alias(f"t{t}") for t in range(subs)])
        psi = w.crossJoin(F.broadcast(total)).select("v", F.array(*[F.get("est", F.lit(t)) / F.col(f"t{t}") for t in range(subs)]).alias("psi"))
        own = g.join(h, "doc_id")
        first = lambda s: F.get("sup", s)  # noqa: E731  the document's total cancels
        second = lambda s, j: F.get("joint", j) / part(s)
    else:
        totals = leaf.groupBy("z").agg(F.count("*").cast("double").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("z", "n"))).alias("t"))
        phi = F.transform("est", lambda e, t: (e + beta) / (F.coalesce(F.col("t")[t], F.lit(0.0)) + types * beta))
        psi = words.crossJoin(F.broadcast(totals)).select("v", phi.alias("psi"))
        first = lambda s: F.get("sup", s) + alpha
        second = lambda s, j: (F.get("joint", j) + gamma_prior) / (F.get("sup", s) + subs * gamma_prior)

    def weigh(j: Column) -> Column:
        s = F.floor(j / subs).cast("int")
        return first(s) * second(s, j) * F.get("psi", F.pmod(j, F.lit(subs)))

    weights = F.transform(F.sequence(F.lit(0), F.lit(size - 1)), weigh)
    drawn = draw(weights, uniform("z", seed, number, F.col("doc_id"), F.col("pos"))).cast("int")
    return toks.drop("z").join(psi, "v").join(own, "doc_id").select("doc_id", "pos", "v", drawn.alias("z"))


def _edge_weights(own: DataFrame, nodes: list[list[str]], prior: float) -> DataFrame:
    """(doc_id, pw): the weight of every path in a document, the product over its edges of the
    smoothed share of the edge among those that leave its node, by whatever way that was reached.
    The root's total is left out, as it is the same for all paths."""
    edges = sorted({e for path in nodes for e in zip(path, path[1:])})
    at = {e: k for k, e in enumerate(edges)}
    on = np.array([[float(e in set(zip(path, path[1:]))) for e in edges] for path in nodes])
    alike = np.array([[float(a[0] == b[0]) for b in edges] for a in edges])
    ways = alike.sum(1)
    root = np.array([e[0] == nodes[0][0] for e in edges])
    places = [[at[e] for e in zip(path, path[1:])] for path in nodes]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = b.column("joint").to_pylist()
            if not rows:
                continue
            n = np.array(rows, float) @ on
            share = (n + prior) / np.where(root, 1.0, n @ alike + ways * prior)
            out = np.ones((len(rows), len(places)))
            for k, path in enumerate(places):
                for e in path:
                    out[:, k] *= share[:, e]
            yield pa.record_batch([b.column("doc_id"), pa.array(out.tolist(), pa.list_(pa.float64()))], names=["doc_id", "pw"])

    return own.select(F.col("doc_id").cast("long").alias("doc_id"), "joint").mapInArrow(run, "doc_id long, pw array<double>")


def path_sweep(toks: DataFrame, nodes: list[list[str]], prior: float, beta: float, types: int, seed: int, number: int, p: SketchParams | None = None) -> DataFrame:
    """Draws the path of every token of toks(doc_id, pos, v, z) anew: z is the place of a path in nodes,
    the lists of nodes that paths() gives, in its order. Paths may differ in length and share
    nodes; a leaf's words are counted over all paths that end there. The paths are the model's,
    held by every task; documents and words stay distributed."""
    smoothed(prior, beta)
    if len({path[0] for path in nodes}) != 1 or min(map(len, nodes)) < 2:
        raise ValueError("paths need one root and an edge each")
    leaves = sorted({path[-1] for path in nodes})
    ends = F.array(*[F.lit(leaves.index(path[-1])) for path in nodes])
    own = _spread(toks.groupBy("doc_id", "z").agg(F.count("*").cast("double").alias("n")), "doc_id", "z", "n", len(nodes)).withColumnRenamed("est", "joint")
    leaf = toks.select("doc_id", "pos", "v", F.get(ends, F.col("z")).alias("z"))
    words = topic_counts(leaf, len(leaves)) if p is None else sketch_vectors(leaf, len(leaves), p)
    totals = leaf.groupBy("z").agg(F.count("*").cast("double").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("z", "n"))).alias("t"))
    phi = F.transform("est", lambda e, t: (e + beta) / (F.coalesce(F.col("t")[t], F.lit(0.0)) + types * beta))
    psi = words.crossJoin(F.broadcast(totals)).select("v", phi.alias("psi"))
    weights = F.transform("pw", lambda x, k: x * F.get("psi", F.get(ends, k)))
    drawn = draw(weights, uniform("z", seed, number, F.col("doc_id"), F.col("pos"))).cast("int")
    return toks.drop("z").join(psi, "v").join(_edge_weights(own, nodes, prior), "doc_id").select("doc_id", "pos", "v", drawn.alias("z"))
