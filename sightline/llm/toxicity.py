"""Toxicity: a counterfactual-regularised linear classifier over words and word beginnings.

Identity terms in labelled texts are swapped for others of their kind, and neutral mentions are added to texts
that have none; the fit penalises the change of the score, so that mentioning a group does not by itself move a score.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices, tidy, trim

#: Identity terms by kind; terms of a kind are swapped for one another.
IDENTITY = {
    "faith": ["christian", "muslim", "jewish", "hindu", "buddhist", "atheist", "christ", "juif", "musulman", "chrétien", "judío", "musulmán", "cristiano", "jude", "moslem"],
    "origin": ["american", "mexican", "german", "french", "african", "asian", "arab", "european", "allemand", "français", "alemán", "francés", "deutscher", "türke", "immigrant", "refugee"],
    "gender": ["woman", "man", "women", "men", "girl", "boy", "transgender", "femme", "homme", "mujer", "hombre", "frau", "mann"],
    "orientation": ["gay", "lesbian", "straight", "bisexual", "homosexual", "heterosexual", "queer"],
    "colour": ["black", "white", "brown"],
    "ability": ["deaf", "blind", "disabled", "autistic"],
    "age": ["old", "young", "elderly", "teenage"],
}
_KIND = {term: kind for kind, terms in IDENTITY.items() for term in terms}
_WORD = re.compile(r"\w+")
_CACHE_ROWS = 200_000
_FLUSH = 60_000


def words_of(text: str | None) -> set[str]:
    return set(_WORD.findall((text or "").lower()))


def features_of(word: str) -> list[str]:
    """The word (marked at its end) and its beginnings of three to six letters."""
    return [word + "$", *(word[:n] for n in range(3, 7) if len(word) > n)]


def swapped(words: set[str], salt: int = 0) -> set[str]:
    """The text's words after each identity term became another one of its kind; without any, with a neutral mention added."""
    out = set()
    for w in words:
        terms = IDENTITY.get(_KIND.get(w, ""), [])
        out.add(terms[(terms.index(w) + 1 + salt % (len(terms) - 1)) % len(terms)] if terms else w)
    if out == words:
        every = list(_KIND)
        out = words | {every[salt % len(every)]}
    return out


@dataclass
class ToxicityModel:
    """Weights of features; the score is the logistic function of bias plus the weights of a text's distinct features."""

    weights: dict[str, float]
    bias: float

    def scorer(self):
        names = {f: i for i, f in enumerate(self.weights)}
        values = np.array(list(self.weights.values()))
        cache: dict[str, tuple[int, ...]] = {}

        def score(text: str | None) -> float:
            found: set[int] = set()
            for w in words_of(text):
                ids = cache.get(w)
                if ids is None:
                    ids = tuple(names[f] for f in features_of(w) if f in names)
                    if len(cache) >= _CACHE_ROWS:
                        cache.clear()
                    cache[w] = ids
                if ids:
                    found.update(ids)
            z = self.bias + float(values[sorted(found)].sum()) if found else self.bias
            return float(1 / (1 + np.exp(-min(40.0, max(-40.0, z)))))

        return score


def _counted(rows: DataFrame) -> DataFrame:
    """feature, toxic documents and other documents that hold it; flushed often, so memory stays bounded."""

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = (Counter(), Counter())

        def flush() -> pa.RecordBatch:
            names = list(dict.fromkeys([*seen[1], *seen[0]]))
            out = pa.RecordBatch.from_arrays(
                [pa.array(names, pa.string()), pa.array([seen[1][f] for f in names], pa.int64()), pa.array([seen[0][f] for f in names], pa.int64())], ["feature", "pos", "neg"]
            )
            for c in seen:
                c.clear()
            return out

        for batch in slices(batches):
            for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                seen[toxic].update({f for w in words_of(text) for f in features_of(w)})
                if len(seen[0]) + len(seen[1]) > _FLUSH:
                    yield flush()
        yield flush()

    return rows.select("text", "toxic").mapInArrow(run, "feature string, pos bigint, neg bigint").groupBy("feature").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))


def fit(docs: DataFrame, labels: DataFrame, sample_rows: int = 6000, features: int = 1500, least_docs: int = 5, least_gain: float = 30.0, penalty: float = 0.5, ridge: float = 0.02, steps: int = 200) -> ToxicityModel:
    """Fit on at most ``sample_rows`` labelled documents of either class, chosen by a hash of doc_id.

    Features enter when a chi-square test of their share among toxic and other documents reaches ``least_gain``, the strongest first.

    ``labels``: (doc_id, toxic 0/1); other values and nulls are left out, and of repeated ids the largest label counts. Class
    weights give the sample the class shares of all labelled rows. Without rows of both classes the model is constant: the
    share of toxic rows, or 0 without any.
    """
    spark = docs.sparkSession
    kind = docs.schema["doc_id"].dataType
    known = labels.where("toxic in (0, 1) and doc_id is not null").withColumn("doc_id", F.col("doc_id").cast(kind)).where("doc_id is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    totals = {r.toxic: r.n for r in known.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    if len(totals) < 2:
        share = totals.get(1, 0) and 1.0
        return ToxicityModel({}, 40.0 if share else -40.0)
    chosen = None
    for c in (0, 1):
        part = known.where(F.col("toxic") == c).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
        chosen = part if chosen is None else chosen.unionByName(part)
    picked = spark.createDataFrame([(r.doc_id, r.toxic) for r in chosen.collect()], f"doc_id {kind.simpleString()}, toxic int")  # 2 * sample_rows at most
    rows = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id")
    sizes = Counter(r[0] for r in picked.select("toxic").collect())
    p, q, r = F.col("pos") / sizes[1], F.col("neg") / sizes[0], (F.col("pos") + F.col("neg")) / (sizes[0] + sizes[1])
    stats = _counted(rows).where(F.col("pos") + F.col("neg") >= least_docs)
    gain = (p - q) * (p - q) / (r * (1 - r) * (1 / sizes[1] + 1 / sizes[0]) + 1e-12)
    best = stats.withColumn("gain", gain).where(F.col("gain") >= least_gain).orderBy(F.desc("gain"), "feature").limit(features).collect()
    names = {r.feature: i for i, r in enumerate(best)}
    for term in _KIND:
        names.setdefault(term + "$", len(names))

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            own, other = [], []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                words = words_of(text)
                turned = swapped(words, zlib.crc32(str(doc_id).encode()))
                for into, ws in ((own, words), (other, turned)):
                    into.append(sorted({names[f] for w in ws for f in features_of(w) if f in names}))
            lists = pa.list_(pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(own, lists), pa.array(other, lists)], ["doc_id", "toxic", "own", "other"])

    data = rows.select("doc_id", "text", "toxic").mapInArrow(run, f"doc_id {kind.simpleString()}, toxic int, own array<int>, other array<int>").orderBy("doc_id").toArrow()  # 2 * sample_rows at most
    y = data["toxic"].to_numpy().astype(float)
    if len(np.unique(y)) < 2:  # the documents with labels are not here
        return ToxicityModel({}, float(np.log((totals[1] + 0.5) / (totals[0] + 0.5))) if len(y) else -40.0)
    share = np.array([totals[int(c)] / sizes[int(c)] for c in y])
    w, b = _descend(data["own"], data["other"], y, share / share.sum(), len(names), penalty, ridge, steps)
    del data
    trim()
    return ToxicityModel({f: float(w[i]) for f, i in names.items()}, float(b))


def _descend(own: pa.ChunkedArray, other: pa.ChunkedArray, y, share, width, penalty, ridge, steps):
    """Weighted logistic loss + ridge + penalty * (score change under the swap)^2, by Adam on the sparse rows (lists of features)."""

    def flat(lists):
        return pc.list_flatten(lists).to_numpy().astype(np.int64), np.repeat(np.arange(len(lists)), pc.list_value_length(lists).to_numpy())

    (ci, cr), (oi, orow) = flat(own), flat(other)
    n = len(y)
    theta, m, v = np.zeros(width + 1), np.zeros(width + 1), np.zeros(width + 1)
    base = np.clip((share * y).sum(), 1e-3, 1 - 1e-3)
    theta[-1] = np.log(base / (1 - base))
    for t in range(1, steps + 1):
        z = np.bincount(cr, theta[ci], n) + theta[-1]
        turned = np.bincount(orow, theta[oi], n) + theta[-1]
        err = share * (1 / (1 + np.exp(-np.clip(z, -40, 40))) - y)
        gap = 2 * penalty * share * (z - turned)
        grad = np.append(
            np.bincount(ci, (err + gap)[cr], width) - np.bincount(oi, gap[orow], width) + ridge / n * theta[:-1] * 2, err.sum()
        )
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad * grad
        theta -= 0.1 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-6)
    return theta[:-1], theta[-1]


def score_texts(docs: DataFrame, model: ToxicityModel, column: str = "score") -> DataFrame:
    """The rows of ``docs`` (text) with the score 0 to 1 in ``column``, which is replaced if there. Null and empty texts get the score of no features."""
    weights, bias = docs.sparkSession.sparkContext.broadcast(model.weights), model.bias  # at most features + identity terms

    @F.arrow_udf("double")
    def scored(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        score = ToxicityModel(weights.value, bias).scorer()
        for texts in batches:
            # some hundred strings at a time
            yield pa.array([score(t) for at in range(0, len(texts), 256) for t in texts.slice(at, 256).to_pylist()], pa.float64())
        trim()

    return docs.drop(column).withColumn(column, scored("text"))
