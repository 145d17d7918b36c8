"""Toxicity by a counterfactual-regularised linear classifier.

Features are the distinct words of a text (lower-cased) and their prefixes of 4
to 8 characters, so that inflected abuse is met. Of the features whose chi-square
with the label is at least ``least`` the best ``terms`` are kept, and every identity
term; without that floor a small labelled set spreads its weight over chance
features. The fit minimises

    weighted log loss + ridge + swap * mean((s(x) - s(x'))^2)

over labelled texts x, where x' is x with each identity term swapped for another
term of its group, or for a neutral word. That pulls the weights of identity
terms together and towards the neutral word, so naming a group is not what makes
a text toxic.

The fit reads a bounded sample: at most ``per_class`` labelled rows of a class
that are not held out, picked by a hash of the id; weights restore the classes'
shares of all such rows. Every whole text is scored.

Defined cases: NULL text is empty; an empty text scores like a text without a
known feature; without labelled rows of both classes the score is their share, or 0.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.llm._common import held_out, map_arrow

PER_CLASS, TERMS, MIN_DF, LEAST, THRESHOLD = 3000, 8192, 4, 15.0, 0.3
PREFIXES = (4, 5, 6, 7, 8)
# Terms that name groups; a swap stays within a line.
IDENTITY = [
    "men women man woman boys girls males females",
    "christian christians muslim muslims jewish jews hindu hindus buddhist atheist atheists catholic",
    "black white asian latino hispanic arab african european american mexican chinese indian",
    "gay lesbian bisexual straight transgender trans queer heterosexual homosexual",
    "immigrant immigrants refugee refugees foreigner foreigners native",
    "old young elderly teenage disabled blind deaf",
    "frauen männer christen muslime juden schwule lesben ausländer",
    "femmes hommes chrétiens musulmans juifs gays lesbiennes étrangers",
    "mujeres hombres cristianos musulmanes judíos homosexuales lesbianas extranjeros",
]
_GROUP = {w: g for g, line in enumerate(IDENTITY) for w in line.split()}
_WORD = re.compile(r"\w+")


def word_features(word: str) -> list[str]:
    """The features of one lower-cased word."""
    if word in _GROUP:
        return [word]
    return [word] + [word[:n] + "*" for n in PREFIXES if len(word) > n]


def text_features(text: str) -> set[str]:
    return {f for w in set(_WORD.findall(text.lower())) for f in word_features(w)}


class Classifier:
    """Weights of at most ``TERMS`` features and the identity terms."""

    def __init__(self, weights: dict[str, float], bias: float):
        self.weights, self.bias = weights, bias
        self.memo: dict[str, tuple] = {}

    def score(self, text: str) -> float:
        memo, weights, hit = self.memo, self.weights, set()
        for w in set(_WORD.findall(text.lower())):
            known = memo.get(w)
            if known is None:
                if len(memo) > 200_000:
                    memo.clear()
                known = memo[w] = tuple(f for f in word_features(w) if f in weights)
            hit.update(known)
        total = self.bias + sum(weights[f] for f in sorted(hit))
        return float(1 / (1 + np.exp(-np.clip(total, -30, 30))))

    def __getstate__(self):
        return {"weights": self.weights, "bias": self.bias, "memo": {}}


def _select(sets: list[set[str]], y: np.ndarray, share: np.ndarray, terms: int, min_df: int, least: float) -> list[str]:
    df, pos = {}, {}
    for s, t, w in zip(sets, y, share):
        for f in s:
            n = df.get(f)
            df[f] = (n[0] + 1, n[1] + w) if n else (1, w)
            if t:
                pos[f] = pos.get(f, 0.0) + w
    p = (share * y).sum() / share.sum()
    total = share.sum()
    ranked = []
    for f, (n, w) in df.items():
        if n >= min_df:
            expect = w * p
            chi = (pos.get(f, 0.0) - expect) ** 2 / max(expect * (1 - p) * (1 - w / total), 1e-9)
            if chi >= least:
                ranked.append((-chi, f))
    ranked.sort()
    return sorted({f for _, f in ranked[:terms]} | set(_GROUP))


def train(sets: list[set[str]], y: np.ndarray, share: np.ndarray, terms: int = TERMS, min_df: int = MIN_DF, least: float = LEAST, ridge: float = 1e-4, swap: float = 1.0, steps: int = 1000) -> Classifier:
    """Fit to feature sets, labels 0/1 and row weights."""
    p = float((share * y).sum() / share.sum())
    if p <= 0 or p >= 1:
        return Classifier({}, 30.0 if p >= 1 else -30.0)
    names = _select(sets, y, share, terms, min_df, least)
    at = {f: i for i, f in enumerate(names)}
    cols = [np.array(sorted(at[f] for f in s if f in at), np.int64) for s in sets]
    row = np.repeat(np.arange(len(cols)), [len(c) for c in cols])
    col = np.concatenate(cols) if cols else np.zeros(0, np.int64)
    # Differences x - x' of the swaps as (pair, feature, sign) entries.
    entries, pairs = [], 0
    for s in sets:
        mine = sorted(f for f in s if f in _GROUP)
        if not mine:
            continue
        for neutral in (False, True):
            for f in mine:
                entries.append((pairs, at[f], 1.0))
                if not neutral:
                    group = IDENTITY[_GROUP[f]].split()
                    entries.append((pairs, at[group[(group.index(f) + 1) % len(group)]], -1.0))
            pairs += 1
    er, ec, es = (np.array(x) for x in zip(*entries)) if entries else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
    weight = share / share.sum()
    w, v, b, vb = np.zeros(len(names)), np.zeros(len(names)), float(np.log(p / (1 - p))), float(np.log(p / (1 - p)))
    # The largest eigenvalues are at most the mean squared norms of the rows.
    norm = float(weight @ np.bincount(row, minlength=len(cols))) + 1.0
    both, own = np.unique(er * len(names) + ec, return_inverse=True) if pairs else (er, er)
    spread = float((np.bincount(own, es, minlength=len(both)) ** 2).sum()) / pairs if pairs else 0.0
    rate = 1.0 / (0.25 * norm + ridge + 2 * swap * spread)
    for k in range(steps):
        z = vb + np.bincount(row, v[col], minlength=len(cols))
        g = weight * (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y)
        grad = np.bincount(col, g[row], minlength=len(names)) + ridge * v
        if pairs:
            gap = np.bincount(er, es * v[ec], minlength=pairs)
            grad += 2 * swap / pairs * np.bincount(ec, es * gap[er], minlength=len(names))
        nw, nb = v - rate * grad, vb - rate * g.sum()
        m = k / (k + 3)
        v, vb, w, b = nw + m * (nw - w), nb + m * (nb - b), nw, nb
    return Classifier({f: float(w[i]) for f, i in at.items() if w[i] != 0.0 or f in _GROUP}, b)


def fit(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> Classifier:
    """Train on a bounded sample of ``labels(doc_id, toxic)`` rows of ``docs``."""
    told = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    told = told.where(~held_out()).withColumn("h", F.pmod(F.xxhash64("doc_id"), F.lit(2**30)))
    counts = {r.toxic: r.n for r in told.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not counts:
        return Classifier({}, -30.0)
    keep = F.lit(False)
    for t, n in counts.items():
        keep = keep | ((F.col("toxic") == t) & (F.col("h") < int(2**30 * min(1.0, per_class / n))))
    sample = told.where(keep).select("doc_id", "toxic", "h")

    def rows(batch):
        sets = [sorted(text_features(t or "")) for t in batch.column(2).to_pylist()]
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(["\n".join(s) for s in sets], pa.string())], ["doc_id", "toxic", "features"])

    # The sample is bounded by 2 * per_class ids, so it is the side to broadcast.
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(sample), "doc_id").select("doc_id", "toxic", "text")
    seen, sets, y = set(), [], []
    for r in map_arrow(texts, rows, "doc_id long, toxic int, features string").orderBy("doc_id").toLocalIterator():
        if r.doc_id not in seen:
            seen.add(r.doc_id)
            sets.append(set(r.features.split("\n")) - {""})
            y.append(1 if r.toxic > 0 else 0)
    if not y:
        return Classifier({}, -30.0)
    y = np.array(y, float)
    n1 = sum(n for t, n in counts.items() if t > 0)
    n0 = sum(counts.values()) - n1
    share = np.where(y > 0, n1 / max(1.0, y.sum()), n0 / max(1.0, (1 - y).sum()))
    return train(sets, y, share)


def _score_batch(shared, threshold: float):
    def fn(batch):
        scores = [shared.value.score(t or "") for t in batch.column(0).to_pylist()]
        cols = [*batch.columns[1:], pa.array(scores, pa.float64()), pa.array([int(s >= threshold) for s in scores], pa.int32())]
        return pa.RecordBatch.from_arrays(cols, [*batch.schema.names[1:], "score", "predicted"])

    return fn


def score_toxicity(docs: DataFrame, model: Classifier, threshold: float = THRESHOLD) -> DataFrame:
    """Per input row ``doc_id, held_out, score, predicted``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    src = docs.select("text", F.col("doc_id").cast("long").alias("doc_id"), held_out().alias("held_out"))
    return map_arrow(src, _score_batch(shared, threshold), "doc_id long, held_out boolean, score double, predicted int")


def op10_toxicity(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return score_toxicity(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
