"""Language identification in two levels: family, then one-versus-one linear SVMs within it.

A text becomes hashed letter n-gram frequencies of its whole length. A one-versus-rest linear
support vector machine picks the language family; within it each pair of languages has an SVM
of its own, and the language with most duels wins (ties: larger sum of margins, then name).
Models are fitted on a bounded sample of labelled rows (``TRAIN_ROWS`` in total, shared evenly
by the labels, at least ``LEAST_PER_LABEL`` each, the rows of smallest id hash); nothing else
is sampled, and every text is read whole. The fitting task holds 16 KB for each of these rows.

Edge cases: a null text or one without a letter is ``und`` with score 0; so is every text if
no labelled row exists; labels without a known family form a family of their own; repeated
rows are predicted alike; other columns are kept, clashing ones overwritten.
"""

from __future__ import annotations

import pickle
import re
from collections.abc import Iterable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F, types as T

from repsum.llm.arrow import add_columns
from repsum.plans.scratch import materialise

DIMENSIONS = 4096
TRAIN_ROWS = 2000
LEAST_PER_LABEL = 40
NONE = "und"

#: Language codes by family.
FAMILIES = {
    "germanic": ("af", "da", "de", "en", "fy", "is", "lb", "nl", "no", "nb", "nn", "sv", "yi"),
    "romance": ("ca", "es", "fr", "gl", "it", "la", "oc", "pt", "ro"),
    "slavic": ("be", "bg", "bs", "cs", "hr", "mk", "pl", "ru", "sk", "sl", "sr", "uk"),
    "uralic": ("et", "fi", "hu"),
    "turkic": ("az", "kk", "ky", "tr", "tt", "uz"),
    "indo-aryan": ("bn", "gu", "hi", "mr", "ne", "pa", "si", "ur"),
    "semitic": ("ar", "he", "mt"),
}
_FAMILY_OF = {code: family for family, codes in FAMILIES.items() for code in codes}

#: Lower-cased ASCII letters and all bytes beyond ASCII; the rest separates words.
_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 97 <= c <= 122 else 32 for c in range(256))
_MAYBE_LETTER = re.compile(r"[^\W\d_]")


def family_of(label: str) -> str:
    return _FAMILY_OF.get(label, f"only:{label}")


def has_letter(text: str) -> bool:
    return any(m.group().isalpha() for m in _MAYBE_LETTER.finditer(text))


def features(text: str, dimensions: int = DIMENSIONS) -> np.ndarray:
    """Unit vector of square-rooted n-gram shares (two and three bytes, spaces at word ends)."""
    words = text.encode("utf-8", "surrogatepass").translate(_TABLE).split()
    raw = np.frombuffer(b" " + b" ".join(words) + b" ", np.uint8)
    counts = np.zeros(dimensions, np.int64)
    for begin in range(0, max(1, len(raw) - 2), 1 << 18):
        a = raw[begin : begin + (1 << 18) + 2].astype(np.uint32)
        two = a[:-1] * np.uint32(257) + a[1:]
        three = two[:-1] * np.uint32(263) + a[2:]
        for gram in (two[: 1 << 18], three):
            counts += np.bincount((gram * np.uint32(2654435761)) >> np.uint32(20) if dimensions == 4096 else gram % np.uint32(dimensions), minlength=dimensions)
    total = counts.sum()
    return np.sqrt(counts / total).astype(np.float32) if total else counts.astype(np.float32)


def fit_svm(x: np.ndarray, y: np.ndarray, ridge: float = 1e-4, rounds: int = 200) -> np.ndarray:
    """Weights (with a bias at the end) of squared-hinge linear SVMs, one column of y (+1/-1) each."""
    x = np.hstack([x, np.ones((len(x), 1), np.float32)])
    share = np.where(y > 0, 0.5 / np.maximum((y > 0).sum(0), 1), 0.5 / np.maximum((y < 0).sum(0), 1)).astype(np.float32)
    w = np.zeros((x.shape[1], y.shape[1]), np.float32)
    ahead, step = w.copy(), np.float32(1 / (4 + ridge))
    for t in range(rounds):
        slack = np.maximum(0, 1 - y * (x @ ahead)) * y * share
        new = ahead - step * (np.float32(ridge) * ahead - 2 * (x.T @ slack))
        ahead = new + np.float32(t / (t + 3)) * (new - w)
        w = new
    return w


class LanguageModel:
    """Family machine and, for each family, the machines of its pairs."""

    def __init__(self, vectors: np.ndarray, labels: list[str]) -> None:
        self.labels = sorted(set(labels))
        self.families = sorted({family_of(x) for x in self.labels})
        kind = np.array([self.families.index(family_of(x)) for x in labels], int)
        self.family_weights = None
        if len(self.families) > 1:
            self.family_weights = fit_svm(vectors, np.where(kind[:, None] == np.arange(len(self.families)), 1.0, -1.0).astype(np.float32))
        named = np.array(labels)
        self.duels: dict[str, tuple[list[str], list[tuple[int, int]], np.ndarray | None]] = {}
        for f in self.families:
            own = [x for x in self.labels if family_of(x) == f]
            pairs = list(combinations(range(len(own)), 2))
            columns = []
            for i, j in pairs:
                rows = np.flatnonzero((named == own[i]) | (named == own[j]))
                columns.append(fit_svm(vectors[rows], np.where(named[rows] == own[i], 1.0, -1.0).astype(np.float32)[:, None]))
            self.duels[f] = own, pairs, np.hstack(columns) if columns else None

    def predict(self, v: np.ndarray) -> tuple[str, float]:
        v = np.append(v, np.float32(1))
        sure = 1.0
        f = self.families[0]
        if self.family_weights is not None:
            margins = v @ self.family_weights
            best = int(np.argmax(margins))
            f = self.families[best]
            gap = float(margins[best] - np.delete(margins, best).max())
            sure = 1 / (1 + np.exp(-2 * gap))
        own, pairs, weights = self.duels[f]
        if weights is None:
            return own[0], float(sure)
        won, sums = np.zeros(len(own)), np.zeros(len(own))
        for (i, j), m in zip(pairs, (v @ weights).tolist()):
            won[i if m >= 0 else j] += 1
            sums[i] += m
            sums[j] -= m
        order = sorted(range(len(own)), key=lambda i: (-won[i], -sums[i], own[i]))
        i, j = order[0], order[1]
        return own[i], float(sure / (1 + np.exp(-4 * (sums[i] - sums[j]) / max(1, len(own) - 1) / 2)))


def training_rows(docs: DataFrame, labelled: str = "lang", total: int = TRAIN_ROWS) -> DataFrame:
    """(label, vector) of the bounded training sample: of each label the rows of smallest id hash.

    Hashes are cut into bins, of which a label's first ones that hold enough rows are kept, so the
    ranking that follows sees little more than it returns, however many rows a label has. Choosing
    reads ids and labels only; the chosen ids, a bounded number, find their texts by a broadcast.
    Null and letterless texts among the chosen rows teach nothing.
    """
    known = docs.where(F.col(labelled).isNotNull()).select(F.col(labelled).alias("label"), F.col("doc_id").cast("long").alias("train_id"), F.xxhash64("doc_id").alias("h"))
    counts = {r["label"]: r["count"] for r in known.groupBy("label").count().collect()}  # one row per label
    each = max(LEAST_PER_LABEL, total // max(1, len(counts)))
    bits = max(1, (4 * max(counts.values(), default=1) // each).bit_length())
    binned = known.withColumn("bin", F.shiftrightunsigned(F.col("h").bitwiseXOR(F.lit(-(1 << 63))), 64 - bits))  # ascends with the signed hash
    sizes = binned.groupBy("label", "bin").count()
    before = F.sum("count").over(Window.partitionBy("label").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1))
    cut = sizes.select("label", "bin", F.coalesce(before, F.lit(0)).alias("before")).where(F.col("before") < each).groupBy("label").agg(F.max("bin").alias("last_bin"))
    near = binned.join(F.broadcast(cut), "label").where(F.col("bin") <= F.col("last_bin"))
    rank = Window.partitionBy("label").orderBy("h", "train_id")
    chosen = materialise(near.withColumn("n", F.row_number().over(rank)).where(F.col("n") <= each).select("train_id").distinct(), "training-ids")
    texts = docs.select(F.col("doc_id").cast("long").alias("train_id"), F.col(labelled).alias("label"), "text").where(F.col("label").isNotNull() & F.col("text").isNotNull())
    # ids are at most each times the labels; a null id teaches nothing
    sample = texts.join(F.broadcast(chosen), "train_id", "left_semi").select("label", "text")

    def work():
        return lambda texts: {"vector": [features(t).tobytes() if has_letter(t) else None for t in texts]}

    return add_columns(sample, "text", [T.StructField("vector", T.BinaryType())], work).select("label", "vector").where("vector is not null")


def fit(docs: DataFrame, labelled: str = "lang", total: int = TRAIN_ROWS) -> LanguageModel | None:
    """Fit in one task on the bounded sample; only the finished weights travel to the driver."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = sorted(r for b in batches for r in zip(b.column("label").to_pylist(), b.column("vector").to_pylist()))
        if rows:
            model = LanguageModel(np.stack([np.frombuffer(v, np.float32) for _, v in rows]), [k for k, _ in rows])
            yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(model)], pa.binary())], names=["model"])

    made = training_rows(docs, labelled, total).repartition(1).mapInArrow(run, "model binary").collect()
    return pickle.loads(made[0]["model"]) if made else None


def predict(docs: DataFrame, model: LanguageModel | None, text_col: str = "text") -> DataFrame:
    """Append lang_pred and score to every row, from the text alone."""

    def work():
        def one(text: str | None) -> tuple[str, float]:
            if model is None or text is None or not has_letter(text):
                return NONE, 0.0
            return model.predict(features(text))

        def step(texts: list) -> dict:
            found = [one(t) for t in texts]
            return {"lang_pred": [x[0] for x in found], "score": [x[1] for x in found]}

        return step

    return add_columns(docs, text_col, [T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())], work)


def held_out(id_col: str = "doc_id"):
    """Rows that no model may learn from: crc32 of the id as text leaves 2 modulo 4."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2, F.lit(False))
