"""Language identification by the nearest of several clustered centroids per language.

A text becomes the TF-IDF vector of its hashed byte bigrams and trigrams, letters only. The
training sample of each language is clustered on the sphere; a text takes the language of
the centroid of highest cosine. One that lies much farther from every centroid than training
texts of its length is rejected.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tallymill.llm.shared import sliced

SIZE = 1 << 13
CENTROIDS = 4
#: Rows of each language in the training sample, as expected by its hash draw.
SAMPLE = 600
#: A text is rejected below this share of the cosine that all but 1 % of training texts of its length reach.
REJECT = 0.5
LENGTHS = 24
_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
_LETTER = regex.compile(r"\p{L}")
UNKNOWN = "und"


def counts(text: bytes) -> np.ndarray:
    """Counts of hashed bigrams and trigrams of lower-case letters; words are set apart."""
    line = b" " + b" ".join(text.translate(_TABLE).split()) + b" "
    c = np.frombuffer(line, np.uint8).astype(np.uint32)
    if len(c) < 3:
        return np.zeros(SIZE, np.float32)
    two = c[:-1] * np.uint32(0x9E3779B1) + c[1:] * np.uint32(0x85EBCA77)
    three = two[:-1] * np.uint32(0xC2B2AE3D) + c[2:] * np.uint32(0x27D4EB2F)
    grams = np.concatenate([two, three])
    grams ^= grams >> np.uint32(15)
    grams *= np.uint32(0x2C1B3C6D)
    return np.bincount(grams >> np.uint32(32 - 13), minlength=SIZE).astype(np.float32)


def _length(size: int) -> int:
    return min(LENGTHS - 1, max(0, int(size)).bit_length())


@dataclass
class Model:
    idf: np.ndarray
    centroids: np.ndarray
    languages: list[str]
    floor: np.ndarray

    def vectors(self, rows: np.ndarray) -> np.ndarray:
        v = np.log1p(rows) * self.idf
        return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)

    def predict(self, texts: list[bytes | None]) -> list[tuple[str, float, bool]]:
        """(language, cosine from 0 to 1, rejected) of each text."""
        out: list[tuple[str, float, bool]] = [(UNKNOWN, 0.0, True)] * len(texts)
        some = [k for k, t in enumerate(texts) if t and _LETTER.search(t.decode("utf-8", "replace"))]
        if not self.languages:
            return out
        for at in range(0, len(some), 256):
            ids = some[at : at + 256]
            near = self.vectors(np.stack([counts(texts[k]) for k in ids])) @ self.centroids.T
            for k, best, cos in zip(ids, near.argmax(1).tolist(), near.max(1).tolist()):
                cos = min(1.0, max(0.0, cos))
                out[k] = (self.languages[best], cos, cos < float(self.floor[_length(len(texts[k]))]))
        return out


def _cluster(v: np.ndarray, k: int, rng: np.random.Generator) -> np.ndarray:
    """Spherical k-means: k or fewer unit centroids."""
    centre = v[[rng.integers(len(v))]]
    while len(centre) < min(k, len(v)):
        far = np.maximum(1 - (v @ centre.T).max(1), 0)
        if far.sum() < 1e-9:
            break
        centre = np.vstack([centre, v[rng.choice(len(v), p=far / far.sum())]])
    for _ in range(20):
        near = (v @ centre.T).argmax(1)
        sums = np.stack([v[near == j].sum(0) for j in range(len(centre))])
        norm = np.linalg.norm(sums, axis=1, keepdims=True)
        centre = np.where(norm > 0, sums / np.maximum(norm, 1e-12), centre)
    return centre.astype(np.float32)


def fit(labelled: DataFrame, per_language: int = SAMPLE, seed: int = 42) -> Model:
    """Learns from labelled(doc_id, text, lang): rows of null text or lang are left out, and of
    each language about per_language rows are drawn by a hash of doc_id and text."""
    rows = labelled.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "text", "lang")
    total = {r[0]: r[1] for r in rows.groupBy("lang").count().collect()}
    share = F.lit(0)
    for lang, n in total.items():
        share = F.when(F.col("lang") == lang, min(1 << 20, -(-per_language * (1 << 20) // n))).otherwise(share)
    drawn = rows.where(F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.lit(1 << 20)) < share)

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, "text"):
            texts = [t.as_py() for t in b.column(0).cast(pa.binary())]
            if texts:
                kept = [counts(t).astype(np.uint32) for t in texts]
                where = [np.flatnonzero(c) for c in kept]
                yield pa.record_batch(
                    [b.column(1), pa.array([len(t) for t in texts], pa.int64()), pa.array([w.astype(np.int32) for w in where], pa.list_(pa.int32())), pa.array([c[w].astype(np.int32) for c, w in zip(kept, where)], pa.list_(pa.int32()))],
                    names=["lang", "size", "gram", "n"],
                )

    got = drawn.select("text", "lang").mapInArrow(features, "lang string, size long, gram array<int>, n array<int>").toArrow().to_pylist()
    got = sorted((r for r in got if r["gram"]), key=lambda r: (r["lang"], r["size"], r["gram"], r["n"]))
    if not got:
        return Model(np.ones(SIZE, np.float32), np.zeros((0, SIZE), np.float32), [], np.zeros(LENGTHS))
    tf = np.zeros((len(got), SIZE), np.float32)
    for k, r in enumerate(got):
        tf[k, r["gram"]] = r["n"]
    idf = (np.log((1 + len(got)) / (1 + (tf > 0).sum(0))) + 1).astype(np.float32)
    model = Model(idf, np.zeros((0, SIZE), np.float32), [], np.zeros(LENGTHS))
    v, lang, rng = model.vectors(tf), np.array([r["lang"] for r in got]), np.random.default_rng(seed)
    parts = []
    for name in sorted(set(lang.tolist())):
        parts.append(_cluster(v[lang == name], CENTROIDS, rng))
        model.languages += [name] * len(parts[-1])
    model.centroids = np.concatenate(parts)
    best, length = (v @ model.centroids.T).max(1), np.array([_length(r["size"]) for r in got])
    low = 0.0
    for k in range(LENGTHS):
        if (length == k).sum() >= 20:
            low = REJECT * float(np.quantile(best[length == k], 0.01))
        model.floor[k] = low
    return model


def _predictor(model: Model) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches, "text"):
            said = model.predict([t.as_py() for t in b.column("text").cast(pa.binary())])
            rest = [b.column(n) for n in b.schema.names]
            new = [pa.array([s[k] for s in said], kind) for k, kind in enumerate((pa.string(), pa.float64(), pa.bool_()))]
            yield pa.record_batch(rest + new, names=[*b.schema.names, "lang_pred", "score", "rejected"])

    return run


def identify(docs: DataFrame, model: Model) -> DataFrame:
    """docs with lang_pred, score and rejected; columns of these names are replaced. Null texts,
    and those without a letter, are `und`, scored 0 and rejected. The model is of fixed size."""
    from pyspark.sql.types import BooleanType, DoubleType, StringType, StructType

    docs = docs.drop("lang_pred", "score", "rejected")
    schema = StructType(list(docs.schema.fields)).add("lang_pred", StringType()).add("score", DoubleType()).add("rejected", BooleanType())
    return docs.mapInArrow(_predictor(model), schema)


def fold(doc_id: Column) -> Column:
    """crc32 of doc_id as text, modulo 4."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(4))
