"""Language identification in two levels: the family first, then one-versus-one linear SVMs inside it.

Features: hashed counts of byte pairs and triples of the lower-cased text with everything but letters as one space,
square-rooted and scaled to length 1. Both levels vote over linear SVMs for all pairs of classes (families, then the
languages of the winning family); ties go to the larger sum of margins. The score is the product of the two levels'
mean sigmoids over the winner's pairs.

Training reads only text and lang of labelled rows, through a documented bound: at most ``per_language`` distinct texts a
language, those with the smallest content hashes. Prediction covers every row and whole texts.

Edge cases: a text that is null or has no letter is ``und`` with score 0; a language without a known family is a family
of its own; with one language learned it is always the answer, with none everything is ``und``; equal texts get equal
results; a null doc_id is not held out and not learned from; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trilist.llm.common import bounded_batches, packed, read_table

PER_LANGUAGE, SIZE = 300, 2048
#: Families of common languages.
FAMILIES = {
    "germanic": "en de nl sv da no nb nn is af yi lb fy",
    "romance": "fr es it pt ro ca gl oc",
    "slavic": "ru uk be pl cs sk sl hr sr bs bg mk",
    "indo-aryan": "hi ur bn pa gu mr ne si",
    "semitic": "ar he am mt",
    "turkic": "tr az kk uz ky tk",
    "uralic": "fi et hu",
    "sinitic": "zh yue",
}


def family_of(lang: str) -> str:
    return next((f for f, langs in FAMILIES.items() if lang.lower().split("-")[0] in langs.split()), lang)


def features(text: str):
    """A vector of 2 * SIZE floats."""
    import numpy as np
    import regex

    plain = " " + regex.sub(r"[^\p{L}\p{M}]+", " ", text.lower()).strip() + " "
    x = np.frombuffer(plain.encode("utf-8", "surrogatepass"), np.uint8).astype(np.uint32)
    pairs = (x[:-1] << 8 | x[1:]) * np.uint32(2654435761) >> np.uint32(21)
    triples = (x[:-2] << 16 | x[1:-1] << 8 | x[2:]) * np.uint32(2246822519) >> np.uint32(21)
    v = np.sqrt(np.r_[np.bincount(pairs, minlength=SIZE), np.bincount(triples, minlength=SIZE)].astype(np.float32))
    return v / max(float(np.linalg.norm(v)), 1e-9)


def svm(x, y, cost: float = 8.0, rounds: int = 12):
    """Weights and bias of an L2-loss linear SVM by dual coordinate descent."""
    import numpy as np

    x = np.c_[x, np.ones(len(x), np.float32)].astype(np.float64)
    w, alpha, diagonal = np.zeros(x.shape[1]), np.zeros(len(x)), 1 / (2 * cost)
    norms, order = (x * x).sum(1) + diagonal, np.random.default_rng(0)
    for _ in range(rounds):
        for i in order.permutation(len(x)):
            step = max(alpha[i] - (y[i] * (x[i] @ w) - 1 + diagonal * alpha[i]) / norms[i], 0.0) - alpha[i]
            if step:
                alpha[i] += step
                w += step * y[i] * x[i]
    return w.astype(np.float32)


class Model:
    """Voting SVMs over families, and inside each family over its languages."""

    def __init__(self, langs: list[str], x):
        import numpy as np

        self.families = {}
        for lang in sorted(set(langs)):
            self.families.setdefault(family_of(lang), []).append(lang)
        langs = np.array(langs)
        fams = np.array([family_of(a) for a in langs])
        self.levels = {"": self._pairs(fams, sorted(self.families), x)}
        for f, members in self.families.items():
            self.levels[f] = self._pairs(langs, members, x)

    @staticmethod
    def _pairs(labels, classes, x):
        import numpy as np

        out = []
        for a, b in combinations(range(len(classes)), 2):
            rows = np.flatnonzero((labels == classes[a]) | (labels == classes[b]))
            out.append((a, b, svm(x[rows], np.where(labels[rows] == classes[a], 1.0, -1.0))))
        return classes, out

    def _vote(self, level: str, v):
        import numpy as np

        classes, pairs = self.levels[level]
        if len(classes) == 1:
            return classes[0], 1.0
        wins, margins, chance = np.zeros(len(classes)), np.zeros(len(classes)), np.zeros(len(classes))
        for a, b, w in pairs:
            m = float(v @ w[:-1] + w[-1])
            wins[a if m > 0 else b] += 1
            margins[a] += m
            margins[b] -= m
            p = 1 / (1 + np.exp(-3 * m))
            chance[a] += p
            chance[b] += 1 - p
        best = max(range(len(classes)), key=lambda k: (wins[k], margins[k]))
        return classes[best], chance[best] / (len(classes) - 1)

    def predict(self, text: str | None) -> tuple[str, float]:
        import regex

        if not text or not self.families or not regex.search(r"\p{L}", text):
            return "und", 0.0
        v = features(text)
        family, p = self._vote("", v)
        lang, q = self._vote(family, v)
        return lang, float(min(1.0, max(0.0, p * q)))


def train(labelled: DataFrame, per_language: int = PER_LANGUAGE) -> Model:
    """Fit on rows (text, lang), at most per_language distinct texts a language, by smallest content hash.

    What is broadcast and collected holds per_language rows a language, and a model for each pair of families: bounded by the number
    of languages, not of documents.
    """
    import numpy as np

    rows = labelled.filter("text IS NOT NULL AND lang IS NOT NULL").select("text", "lang", F.xxhash64("text").alias("h"))
    # hashes are uniform: of d distinct ones, about 3 * per_language lie in this share of their range, so few meet in one task
    hashes = rows.select("lang", "h").distinct()
    share = hashes.groupBy("lang").agg((F.lit(3.0 * per_language) / F.count("*")).alias("share"))
    near = hashes.join(F.broadcast(share), "lang").filter((F.col("h") / 2.0**64 + 0.5) <= F.col("share"))
    place = F.row_number().over(Window.partitionBy("lang").orderBy("h"))
    few = near.withColumn("place", place).filter(F.col("place") <= per_language).select("lang", "h")
    few = rows.join(F.broadcast(few), ["lang", "h"]).groupBy("lang", "h").agg(F.first("text").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [features(t).astype(np.float16).tobytes() for t in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(found, pa.binary())], names=["lang", "h", "v"])

    got = sorted(few.select("lang", "h", "text").mapInArrow(run, "lang string, h long, v binary").collect(), key=lambda r: (r.lang, r.h))
    if not got:
        return Model([], np.zeros((0, 2 * SIZE), np.float32))
    return Model([r.lang for r in got], np.stack([np.frombuffer(r.v, np.float16).astype(np.float32) for r in got]))


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """Rows (doc, lang_pred, score) with the row of docs as a struct."""
    bounded_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [model.predict(t) for t in b.column(0).field("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x for x, _ in found], pa.string()), pa.array([s for _, s in found], pa.float64())], names=["doc", "lang_pred", "score"])

    rows = packed(docs).select("doc")
    return rows.mapInArrow(run, f"doc {rows.schema['doc'].dataType.simpleString()}, lang_pred string, score double")


def held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))


def op5_family_svm(spark, sf_dir: str) -> DataFrame:
    """Learn from three quarters of the documents, predict all of them."""
    docs = read_table(spark, sf_dir, "documents")
    model = train(docs.filter(F.col("doc_id").isNotNull() & ~held_out()).select("text", "lang"))
    done = predict(docs.select("doc_id", "text"), model).select("doc.doc_id", "lang_pred", "score")
    return done.select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
