"""Language identification in two steps: family, then one-versus-one inside it.

Features are hashed counts of one to three adjacent characters, lower-cased, with
everything but letters as one separator, square-rooted and scaled to length 1. A
linear support vector machine per family tells families apart; inside a family
one machine per pair of languages decides by votes of calibrated margins.

The machines are fitted on a bounded sample: at most ``per_language`` rows of a
language, ``most`` rows in all and the ``languages`` most frequent values of lang
(a dirty column may hold any number), picked by a hash of the id, from rows that are
not held out; whole texts are used. Prediction reads every whole text.

Defined cases: NULL texts and texts without a letter are ``und`` with score 0, and
so is everything if nothing was learned; with one language all other texts are
that language with score 1. Equal texts get equal answers.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cutfold.llm._common import held_out, map_arrow, schema_with, slices

DIM, PER_LANGUAGE, MOST, LANGUAGES = 4096, 500, 2400, 200
# Families of closely related languages.
FAMILIES = {
    "germanic": "en de nl af sv da no nb nn is fy lb yi",
    "romance": "fr es it pt ro ca gl oc la",
    "slavic": "ru uk be pl cs sk bg sr hr bs sl mk",
    "baltic": "lt lv",
    "celtic": "ga gd cy br",
    "uralic": "fi et hu",
    "turkic": "tr az kk ky uz tk tt",
    "indic": "hi mr ne bn pa gu ur si",
    "iranian": "fa ps ku tg",
    "dravidian": "ta te kn ml",
    "semitic": "ar he am mt",
    "austronesian": "id ms tl jv mg",
}
_FAMILY = {code: name for name, codes in FAMILIES.items() for code in codes.split()}

_tables: list[np.ndarray] = []


def _folded() -> np.ndarray:
    """Per code point its lower-case letter, or 0 if it is not a letter."""
    if not _tables:
        table = np.zeros(0x110000, np.uint32)
        for i in range(0x110000):
            c = chr(i)
            if c.isalpha():
                low = c.lower()
                table[i] = ord(low) if len(low) == 1 else i
        _tables.append(table)
    return _tables[0]


def family_of(lang: str) -> str:
    """The family of a language code; an unknown code is a family of its own."""
    return _FAMILY.get(lang.split("-")[0].lower(), lang)


def features(texts: list[str], dim: int = DIM) -> tuple[np.ndarray, np.ndarray]:
    """A float32 row per text, and whether the text has a letter."""
    flat = _folded()[np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32)].astype(np.uint64)
    lens = np.array([len(t) for t in texts])
    doc = np.repeat(np.arange(len(texts)), lens)
    letters = np.bincount(doc[flat > 0], minlength=len(texts))
    counts = np.zeros(len(texts) * dim)
    shift = np.uint64(64 - int(dim).bit_length() + 1)
    gram = np.zeros(len(flat), np.uint64)
    any_letter = np.zeros(len(flat), bool)
    with np.errstate(over="ignore"):
        for n in (1, 2, 3):
            m = len(flat) - n + 1
            if m <= 0:
                break
            gram = gram[:m] * np.uint64(0x110001) + flat[n - 1 :] + np.uint64(1)
            any_letter = any_letter[:m] | (flat[n - 1 :] > 0)
            ok = any_letter & (doc[:m] == doc[n - 1 :])
            bucket = ((gram[ok] * np.uint64(0x9E3779B97F4A7C15)) >> shift).astype(np.int64)
            counts += np.bincount(doc[:m][ok] * dim + bucket, minlength=len(counts))
    x = np.sqrt(counts.reshape(len(texts), dim))
    norm = np.linalg.norm(x, axis=1, keepdims=True)
    return (x / np.maximum(norm, 1e-12)).astype(np.float32), letters > 0


def fit_svm(x: np.ndarray, y: np.ndarray, c: float = 8.0, steps: int = 120) -> tuple[np.ndarray, float, float, float]:
    """A linear machine with squared hinge loss, classes weighted equally, and the
    slope and offset of a logistic fit to its margins. ``y`` is +1 or -1."""
    n = len(y)
    share = np.where(y > 0, 0.5 / max(1, (y > 0).sum()), 0.5 / max(1, (y < 0).sum()))
    xa = np.hstack([x, np.ones((n, 1), np.float32)])
    w, v = np.zeros(xa.shape[1]), np.zeros(xa.shape[1])
    rate = 1.0 / (1.0 + 2 * c * float((xa**2).sum(axis=1).max()))
    for k in range(steps):
        slack = np.maximum(0, 1 - y * (xa @ v))
        nxt = v - rate * (v - 2 * c * (xa.T @ (share * y * slack)))
        v, w = nxt + k / (k + 3) * (nxt - w), nxt
    margin = xa @ w
    slope, offset = 2.0, 0.0
    target = np.where(y > 0, 1 - 1e-3, 1e-3)
    for _ in range(200):
        p = 1 / (1 + np.exp(-np.clip(slope * margin + offset, -30, 30)))
        slope -= 4.0 * (share * (p - target) * margin).sum()
        offset -= 4.0 * (share * (p - target)).sum()
    return w[:-1].astype(np.float32), float(w[-1]), float(max(slope, 0.1)), float(offset)


class Hierarchy:
    """The fitted machines: bounded by the number of languages and ``DIM``."""

    def __init__(self, x: np.ndarray, langs: list[str]):
        self.langs = sorted(set(langs))
        lang = np.array(langs)
        fam = np.array([family_of(v) for v in langs])
        self.families = sorted(set(fam.tolist()))
        self.members = {f: [v for v in self.langs if family_of(v) == f] for f in self.families}
        self.by_family = [fit_svm(x, np.where(fam == f, 1.0, -1.0)) for f in self.families] if len(self.families) > 1 else []
        self.pairs = {}
        for f in self.families:
            for a, b in combinations(self.members[f], 2):
                use = (lang == a) | (lang == b)
                self.pairs[a, b] = fit_svm(x[use], np.where(lang[use] == a, 1.0, -1.0))

    @staticmethod
    def _p(m, x):
        return 1 / (1 + np.exp(-np.clip(m[2] * (x @ m[0] + m[1]) + m[3], -30, 30)))

    def predict(self, x: np.ndarray) -> tuple[list[str], np.ndarray]:
        n = len(x)
        fam = np.stack([self._p(m, x) for m in self.by_family], 1) if self.by_family else np.ones((n, 1))
        fam = fam / fam.sum(axis=1, keepdims=True)
        best = fam.argmax(axis=1)
        out, score = [""] * n, np.zeros(n)
        for k, f in enumerate(self.families):
            rows = np.flatnonzero(best == k)
            names = self.members[f]
            votes = np.ones((len(rows), len(names)))
            if len(names) > 1:
                votes = np.zeros((len(rows), len(names)))
                for (a, b), m in ((p, m) for p, m in self.pairs.items() if p[0] in names):
                    p = self._p(m, x[rows])
                    votes[:, names.index(a)] += p
                    votes[:, names.index(b)] += 1 - p
                votes /= len(names) - 1
            win = votes.argmax(axis=1)
            for r, i in zip(rows, win):
                out[r] = names[i]
            score[rows] = fam[rows, k] * votes[np.arange(len(rows)), win]
        return out, np.clip(score, 0, 1)


def fit(docs: DataFrame, per_language: int = PER_LANGUAGE, most: int = MOST, languages: int = LANGUAGES) -> Hierarchy | None:
    usable = docs.select(F.xxhash64(F.col("doc_id")).alias("h"), "lang", "text", held_out().alias("out")).where("not out and lang is not null and text is not null")
    counts = usable.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy(F.col("n").desc(), "lang").limit(languages).collect()
    if not counts:
        return None
    each = max(1, min(per_language, most // len(counts)))
    shares = [(r.lang, int(2**30 * min(1.0, 1.3 * each / r.n + 20 / r.n))) for r in counts]
    shares = docs.sparkSession.createDataFrame(shares, "lang string, upto long")
    sample = usable.join(F.broadcast(shares), "lang").where(F.pmod("h", F.lit(2**30)) < F.col("upto"))

    def rows(batch):
        h, lang, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()
        for lo, hi in slices(texts, 500_000):
            for a in range(lo, hi, 256):
                b = min(hi, a + 256)
                x, ok = features(texts[a:b])
                good = np.flatnonzero(ok)
                yield pa.RecordBatch.from_pydict({"h": pa.array([h[a + i] for i in good], pa.int64()), "lang": pa.array([lang[a + i] for i in good], pa.string()), "x": pa.array([x[i].tobytes() for i in good], pa.binary())})

    got = sorted(((r.lang, r.h, bytes(r.x)) for r in map_arrow(sample.select("h", "lang", "text"), rows, "h long, lang string, x binary").collect()))
    used, taken = [], {}
    for lang, _, x in got:
        if taken.get(lang, 0) < each:
            taken[lang] = taken.get(lang, 0) + 1
            used.append((lang, x))
    if not used:
        return None
    return Hierarchy(np.stack([np.frombuffer(x, np.float32) for _, x in used]), [v for v, _ in used])


def _predict(shared):
    def fn(batch):
        model = shared.value
        texts = [t or "" for t in batch.column(0).to_pylist()]
        langs, scores = [], []
        for lo, hi in slices(texts, 500_000):
            for a in range(lo, hi, 256):
                part = texts[a : min(hi, a + 256)]
                x, ok = features(part)
                name, p = model.predict(x) if model else (["und"] * len(part), np.zeros(len(part)))
                langs += [v if g else "und" for v, g in zip(name, ok)]
                scores += np.where(ok, p, 0.0).tolist()
        cols = [*batch.columns[1:], pa.array(langs, pa.string()), pa.array(scores, pa.float64())]
        return pa.RecordBatch.from_arrays(cols, [*batch.schema.names[1:], "lang_pred", "score"])

    return fn


def predict_language(docs: DataFrame, model: Hierarchy | None, *keep: Column) -> DataFrame:
    """The ``keep`` columns with ``lang_pred`` and ``score``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    src = docs.select("text", *keep)
    return map_arrow(src, _predict(shared), schema_with(src, 1, "lang_pred string, score double"))


def reject_unknown(docs: DataFrame, min_score: float = 0.0) -> DataFrame:
    """The input rows and columns whose text has a language, by the fit on ``docs``
    itself; ``und`` texts and scores below ``min_score`` go."""
    kept = predict_language(docs, fit(docs), F.struct("*").alias("_row"))
    return kept.where((F.col("lang_pred") != "und") & (F.col("score") >= min_score)).select("_row.*")


def op4_language_id(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return predict_language(docs, fit(docs), F.col("doc_id").cast("long").alias("doc_id"), held_out().alias("held_out"))
