"""Language identification by a two-level hierarchy of linear classifiers.

Byte trigrams, hashed, are the features. One-versus-one linear support vector
machines first choose the language family, others then separate the languages
within it. A text's margins are sums of trigram weights over its whole length.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from densegrid.llm._text import column, slices
from densegrid.plans.shipping import ship

BITS, SCALE = 13, 10.0
#: Documents per language that the classifiers are fitted on, in expectation; twice that at most.
PER_LANGUAGE = 600
UNKNOWN = "und"

# Families of common languages by their ISO 639-1 codes. Others stand alone.
FAMILIES = {
    "germanic": "af da de en fy is lb nl no nb nn sv yi", "romance": "ca es fr gl it la oc pt ro",
    "slavic": "be bg bs cs hr mk pl ru sk sl sr uk", "uralic": "et fi hu", "baltic": "lt lv",
    "indic": "bn gu hi mr ne pa ur", "turkic": "az kk ky tr tt uz", "semitic": "am ar he mt", "celtic": "br cy ga gd",
}
_FAMILY = {lang: family for family, langs in FAMILIES.items() for lang in langs.split()}
_LETTER = re.compile(rb"[A-Za-z]")


def held_out(doc_id: Column, folds: int, fold: int) -> Column:
    """crc32 of the id as text, modulo ``folds``, is ``fold``; false for a null id."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds)) == fold, F.lit(False))


def has_letter(text: bytes | None) -> bool:
    """Whether a text has a letter in the sense of Unicode; digits raised, circled or broken are none."""
    return bool(text) and (bool(_LETTER.search(text)) or any(map(str.isalpha, text.decode("utf-8", "replace"))))


def hash_share(doc_id: Column, salt: str) -> Column:
    """A value in 0..1 drawn from the id."""
    return F.xxhash64(F.lit(salt), doc_id).bitwiseAND(F.lit((1 << 30) - 1)) / float(1 << 30)


def trigrams(texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed trigrams of the texts, each padded by spaces, and where each text's begin (and all end)."""
    whole = b"".join(b" " + (t or b"").lower() + b"  " for t in texts)  # the last space only parts texts
    b = np.frombuffer(whole, np.uint8).astype(np.uint32)
    h = ((b[:-2] << np.uint32(16) | b[1:-1] << np.uint32(8) | b[2:]) * np.uint32(2654435761)) >> np.uint32(32 - BITS)
    sizes = np.fromiter((len(t or b"") + 3 for t in texts), np.int64, len(texts))
    return h, np.concatenate([[0], np.cumsum(sizes)])


def sample_features(labelled: DataFrame) -> list[tuple[str, np.ndarray, np.ndarray]]:
    """(label, trigram, share) of a frame (label, text) small enough to hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            labels, idx, val = [], [], []
            for label, t in zip(column(batch, "label"), column(batch, "text"), strict=True):
                h, ends = trigrams([t])
                found, n = np.unique(h[: ends[1] - 2], return_counts=True)
                if len(found):
                    labels.append(label)
                    idx.append(found.astype(np.int32).tobytes())
                    val.append((n * (SCALE / n.sum())).astype(np.float32).tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(labels, pa.string()), pa.array(idx, pa.binary()), pa.array(val, pa.binary())], ["label", "idx", "val"])

    rows = labelled.mapInArrow(run, "label string, idx binary, val binary").collect()
    return sorted(((r["label"], np.frombuffer(r["idx"], np.int32), np.frombuffer(r["val"], np.float32)) for r in rows), key=lambda x: (x[0], x[1].tobytes(), x[2].tobytes()))


def fit_svm(rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, c: float = 10.0, rounds: int = 30) -> np.ndarray:
    """Weights, the last one a bias, of a linear SVM with squared hinge loss: dual coordinate descent.

    ``rows`` are sparse (indices, values). Classes weigh alike whatever their sizes.
    """
    weight = np.where(y > 0, len(y) / (2 * max(1, (y > 0).sum())), len(y) / (2 * max(1, (y < 0).sum())))
    slack = 1 / (2 * c * weight)
    norm, alpha, w = np.array([1 + float((v * v).sum()) for _, v in rows]) + slack, np.zeros(len(rows)), np.zeros((1 << BITS) + 1)
    rng = np.random.default_rng(7)
    for _ in range(rounds):
        for i in rng.permutation(len(rows)):
            idx, val = rows[i]
            g = y[i] * (val @ w[idx] + w[-1]) - 1 + slack[i] * alpha[i]
            new = max(0.0, alpha[i] - g / norm[i])
            if new != alpha[i]:
                step = (new - alpha[i]) * y[i]
                w[idx] += step * val
                w[-1] += step
                alpha[i] = new
    return w


def margins(rows: list[tuple[np.ndarray, np.ndarray]], w: np.ndarray) -> np.ndarray:
    return np.array([val @ w[idx] for idx, val in rows]) + w[-1]


def fit_sigmoid(margin: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Platt's a, b: P(y = 1) = 1 / (1 + exp(-(a m + b))), with his softened targets."""
    up, down = (y > 0).sum(), (y < 0).sum()
    t = np.where(y > 0, (up + 1) / (up + 2), 1 / (down + 2))
    a, b = 1.0, 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -30, 30)))
        d, s = p - t, p * (1 - p) + 1e-9
        g = np.array([(d * margin).sum(), d.sum()])
        h = np.array([[(s * margin**2).sum() + 1e-6, (s * margin).sum()], [(s * margin).sum(), s.sum() + 1e-6]])
        step = np.linalg.solve(h, g)
        a, b = a - step[0], b - step[1]
        if abs(step).max() < 1e-7:
            break
    return float(max(a, 1e-3)), float(b)


class LanguageModel:
    """Pairwise classifiers among families and, within each family, among its languages."""

    def __init__(self, rows: list[tuple[str, np.ndarray, np.ndarray]]):
        labels = np.array([r[0] for r in rows], object)
        sparse = [(idx, val.astype(np.float64)) for _, idx, val in rows]
        self.languages = sorted(set(labels.tolist()))
        family = {lang: _FAMILY.get(lang, lang) for lang in self.languages}
        self.families = {f: [lang for lang in self.languages if family[lang] == f] for f in sorted(set(family.values()))}
        kin = np.array([family[lang] for lang in labels], object)
        self.pairs: dict[tuple[str, str], int] = {}
        weights, self.sigmoid = [], []
        for of, names in [(kin, list(self.families)), *((labels, langs) for langs in self.families.values())]:
            for a, b in combinations(names, 2):
                take = np.flatnonzero((of == a) | (of == b))
                y, x = np.where(of[take] == a, 1.0, -1.0), [sparse[i] for i in take]
                w = fit_svm(x, y)
                self.pairs[("f:" if of is kin else "l:") + a, b] = len(weights)
                self.sigmoid.append(fit_sigmoid(margins(x, w), y))
                weights.append(w)
        stacked = np.array(weights).reshape(-1, (1 << BITS) + 1)
        self.weights, self.bias = np.ascontiguousarray(stacked[:, :-1].T, np.float32) * np.float32(SCALE), stacked[:, -1]

    def _choose(self, prob: np.ndarray, kind: str, names: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Index of the name with most pairwise wins (ties: largest sum), and its least pairwise probability."""
        n = len(names)
        table = np.full((len(prob), n, n), np.nan)
        for i, j in combinations(range(n), 2):
            p = prob[:, self.pairs[kind + names[i], names[j]]]
            table[:, i, j], table[:, j, i] = p, 1 - p
        if n == 1:
            return np.zeros(len(prob), np.int64), np.ones(len(prob))
        total = (table >= 0.5).sum(axis=2) + np.nansum(table, axis=2) / n
        best = total.argmax(axis=1)
        return best, np.nanmin(table[np.arange(len(prob)), best], axis=1)

    def predict(self, texts: list[bytes | None]) -> tuple[list[str], np.ndarray]:
        """A language and a score in 0..1 for each text; texts without a letter: 'und', 0."""
        names, scores = [], []
        for s, e in slices(texts):
            part = texts[s:e]
            h, ends = trigrams(part)
            count = np.diff(ends) - 2
            margin = np.tile(self.bias, (len(part), 1))
            for k in range(len(self.bias)):
                sums = np.concatenate([[0.0], np.cumsum(self.weights[:, k][h], dtype=np.float64)])
                margin[:, k] += (sums[ends[1:] - 2] - sums[ends[:-1]]) / count
            a, b = np.array(self.sigmoid).reshape(-1, 2).T
            prob = 1 / (1 + np.exp(-np.clip(a * margin + b, -50, 50)))
            family, sure = self._choose(prob, "f:", list(self.families))
            lang = np.empty(len(part), object)
            for f, (_, langs) in enumerate(self.families.items()):
                at = np.flatnonzero(family == f)
                if len(at):
                    best, p = self._choose(prob[at], "l:", langs)
                    lang[at], sure[at] = np.array(langs, object)[best], sure[at] * p
            for i, t in enumerate(part):
                if not has_letter(t):
                    lang[i], sure[i] = UNKNOWN, 0.0
            names += lang.tolist()
            scores.append(sure)
        return names, np.clip(np.concatenate([*scores, np.zeros(0)]), 0.0, 1.0)


def train(docs: DataFrame, text: str = "text", per_language: int = PER_LANGUAGE) -> LanguageModel:
    """Fits on documents with a language outside the held-out fold, about ``per_language`` of each language.

    Only which documents are sampled depends on their ids; only texts are features.
    No labelled documents at all: every text is 'und'.
    """
    open_rows = docs.where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"), 5, 0))
    counts = {r["lang"]: r["n"] for r in open_rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return LanguageModel([])
    share = F.create_map(*[F.lit(x) for lang, n in sorted(counts.items()) for x in (lang, min(1.0, per_language / n))])
    some = open_rows.where(hash_share(F.col("doc_id"), "language") < share[F.col("lang")])
    some = some.select(F.col("lang").alias("label"), F.col(text).cast("binary").alias("text"))
    return LanguageModel(sample_features(some.limit(2 * per_language * len(counts))))


def annotate(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id") -> DataFrame:
    """``docs`` with held_out, lang_pred and score added (columns of these names are replaced).

    The whole text is read; all columns pass through the same task, no join.
    """
    shipped, added = ship(docs.sparkSession, model), ("held_out", "lang_pred", "score")
    kept = docs.select(*[F.col(f"`{c}`") for c in docs.columns if c not in added])
    rows = kept.withColumn("held_out", held_out(F.col(id_col), 5, 0))
    schema = T.StructType([*rows.schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    place = kept.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here = shipped()
        for batch in batches:
            texts = batch.column(place).cast(pa.binary()).to_pylist()
            names, scores = here.predict(texts) if here.languages else ([UNKNOWN] * len(texts), np.zeros(len(texts)))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(names, pa.string()), pa.array(scores)], [*batch.schema.names, "lang_pred", "score"])

    return rows.mapInArrow(run, schema)


def identify(docs: DataFrame, model: LanguageModel | None = None) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row; the whole text is read.

    lang_pred is a learned language, or 'und' with score 0 where the text is null
    or has no letter. A null doc_id is not held out and not learned from. Repeated
    rows stay; other columns are ignored; no rows give no rows.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return annotate(rows, model or train(docs)).select("doc_id", "held_out", "lang_pred", "score")
