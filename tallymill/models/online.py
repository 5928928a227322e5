"""Topics of a stream whose vocabulary is not known: one sweep over each micro-batch.

Words are keys by fingerprint, counts are sketches of fixed size, and the number of word types,
which smoothing needs, comes from a distinct-count sketch that grows with the stream.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallymill.models.lda import Topics, merged, one_pass, start
from tallymill.operators.matrix import RowSketches
from tallymill.params import smoothed
from tallymill.plans.lineage import cut, drop


@dataclass
class OnlineTopics:
    """Give update() to foreachBatch of a stream of (doc_id, vs), vs being word fingerprints. What is
    held is one sketch, topic totals and a distinct-count sketch, all of a size the stream does not
    change. A batch that comes again after a failure is not counted twice."""

    matrix: RowSketches
    alpha: float = 0.1
    beta: float = 0.1
    seed: int = 42
    passes: int = 2
    topics: Topics | None = None
    distinct: bytes | None = None
    log: list[dict] = field(default_factory=list)

    def __post_init__(self) -> None:
        smoothed(self.alpha, self.beta)

    def update(self, batch: DataFrame, batch_id: int) -> None:
        if self.log and batch_id <= self.log[-1]["batch"]:
            return
        words = batch.select(F.explode("vs").alias("v")).agg(F.hll_sketch_agg("v").alias("s"), F.count("*").alias("n"))
        if self.distinct is not None:
            words = words.select(F.hll_union("s", F.lit(self.distinct)).alias("s"), "n")
        self.distinct, types, tokens = words.select("s", F.hll_sketch_estimate("s"), "n").first()
        if not tokens:
            return
        docs, former = start(batch, self.matrix.components, self.seed + batch_id), None
        read = self.topics and Topics(self.matrix, self.topics.flat, self.topics.totals, self.beta, types)
        # the first batch has nothing to read yet, so its own counts are read from the second pass on
        for sweep in range(self.passes):
            done = cut(one_pass(docs, self.matrix, self.alpha, self.seed + batch_id, sweep + 1, read), "online")
            flat, totals, _ = merged(done, self.matrix, self.seed + batch_id, sweep)
            if former is not None:
                drop(former)
            former, docs = done, done.where("block IS NULL").select("doc_id", "vs", "zs")
            both = self._with(flat, totals, batch_id)
            read = Topics(self.matrix, both[0], both[1], self.beta, types)
        drop(former)
        self.topics = read
        self.log.append({"batch": batch_id, "types": int(types), "tokens": int(tokens), "total": int(read.totals.sum())})

    def _with(self, flat: np.ndarray, totals: np.ndarray, step: int) -> tuple[np.ndarray, np.ndarray]:
        if self.topics is None:
            return flat, totals
        return self.matrix.join(self.topics.flat, flat, self.seed, step, 0), self.topics.totals + totals
