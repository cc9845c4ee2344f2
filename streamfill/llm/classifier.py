"""Quality classifier: ordinal regression with a cumulative logit link on graded ratings.

Grades are ordered: 0 toxic, 1 low quality, 2 good. One weight vector over hashed words and a few measures of form
is shared by all grades; ordered thresholds part them: P(grade > j) = sigmoid(score - threshold_j). The expected
grade and the probability of the top grade come out for every document, and selection is by the latter.

A document's different words count once each, and their sum is divided by the fourth root of their number, so that
a few bad words in a long text still tell. Buckets that few documents of the sample hold have no weight. The model is fitted on the driver on at most `sample` labelled documents, those with the least hashes of their
ids; everything is scored. Without labels every document has a probability over one half and is kept.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import light

BUCKETS = 1 << 18
SAMPLE = 8000
#: Documents of the sample that must hold a bucket for it to have a weight.
LEAST_DOCUMENTS = 5
REMEMBERED = 400_000
#: Measures of form; see `form`.
FORMS = 9
TRIM = ".,;:!?\"'()[]{}*#$%&|<>-_"


def bucket(word: str) -> int:
    from xxhash import xxh32_intdigest

    return xxh32_intdigest(word.encode()) % BUCKETS


def normal(token: str) -> str:
    return token.strip(TRIM).lower()


@cache
def alphabetic() -> np.ndarray:
    """Whether each code point is a letter."""
    return np.fromiter((chr(k).isalpha() for k in range(0x110000)), bool, 0x110000)


def letters_of(text: str) -> int:
    return int(alphabetic()[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)].sum())


def form(text: str, tokens: list[str]) -> np.ndarray:
    """Shares of capitals, digits, symbols and punctuation, of different words and of short tokens, and of length."""
    n, m = max(1, len(text)), max(1, len(tokens))
    letters = letters_of(text)
    upper = len(re.findall("[A-ZÀ-ÖØ-Þ]", text))
    return 5 * np.array([
        1.0,
        upper / max(1, letters),
        len(re.findall("[0-9]", text)) / n,
        min(1.0, len(re.findall(r"[#*$%&|<>!]", text)) / m),
        len(set(tokens)) / m,
        min(1.0, m / 10) if m < 10 else 1.0,
        min(1.0, text.count("\n") / m),
        sum(a == b for a, b in zip(tokens, tokens[1:], strict=False)) / m,
        min(1.0, n / m / 20),
    ])


@dataclass
class Model:
    """Weights of the hashed words, of the measures of form, and the thresholds between grades, ascending."""

    words: np.ndarray
    forms: np.ndarray
    thresholds: np.ndarray

    def grades(self, scores: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(expected grade, probability of the top grade) of each score."""
        above = 1 / (1 + np.exp(-(scores[:, None] - self.thresholds[None, :])))
        return above.sum(axis=1), above[:, -1]


def features(text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(buckets, values, form) of one text."""
    tokens = text.split()
    at, counts = np.unique([bucket(w) for w in set(map(normal, tokens)) if w], return_counts=True)
    return at.astype(np.int64), counts / damping(int(counts.sum())), form(text, tokens)


def damping(different: int) -> float:
    return max(1, different) ** 0.25


def fit(texts: list[str], grades: list[int], n_grades: int = 3, epochs: int = 100, rate: float = 0.3, decay: float = 1e-4, least_documents: int = LEAST_DOCUMENTS) -> Model:
    """Full-batch Adam on the log-likelihood; thresholds are kept apart by learning the logs of their steps."""
    if not texts:
        return Model(np.zeros(BUCKETS, np.float32), np.zeros(FORMS), -np.arange(n_grades - 1, 0, -1.0))
    rows = [features(t) for t in texts]
    size = [len(r[0]) for r in rows]
    doc = np.repeat(np.arange(len(rows)), size)
    at, value = np.concatenate([r[0] for r in rows]), np.concatenate([r[1] for r in rows])
    common = np.bincount(at, minlength=BUCKETS)[at] >= least_documents
    doc, at, value = doc[common], at[common], value[common]
    forms, grade = np.stack([r[2] for r in rows]), np.asarray(grades)
    weight = 1 / np.maximum(1, np.bincount(grade, minlength=n_grades))[grade]
    weight /= weight.sum()
    theta = [np.zeros(BUCKETS), np.zeros(FORMS), np.zeros(1), np.zeros(n_grades - 2)]
    m, v = [np.zeros_like(x) for x in theta], [np.zeros_like(x) for x in theta]
    for step in range(1, epochs + 1):
        w, f, first, gaps = theta
        cuts = first + np.concatenate([[0.0], np.cumsum(np.exp(gaps))])
        score = np.bincount(doc, w[at] * value, minlength=len(rows)) + forms @ f
        up = 1 / (1 + np.exp(-(score[:, None] - cuts[None, :])))
        full = np.concatenate([np.ones((len(rows), 1)), up, np.zeros((len(rows), 1))], axis=1)
        slope = full * (1 - full)
        every = np.arange(len(rows))
        share = np.maximum(full[every, grade] - full[every, grade + 1], 1e-9)
        g_score = -weight * (slope[every, grade] - slope[every, grade + 1]) / share
        g_cut = np.zeros(n_grades - 1)
        for j in range(n_grades - 1):
            g_cut[j] = (weight * slope[:, j + 1] / share * ((grade == j + 1).astype(float) - (grade == j).astype(float))).sum()
        later = np.cumsum(g_cut[::-1])[::-1]
        grads = [np.bincount(at, g_score[doc] * value, minlength=BUCKETS) + decay * w, forms.T @ g_score, later[:1], later[1:] * np.exp(gaps)]
        for k, g in enumerate(grads):
            m[k] = 0.9 * m[k] + 0.1 * g
            v[k] = 0.99 * v[k] + 0.01 * g * g
            theta[k] = theta[k] - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)
    w, f, first, gaps = theta
    return Model(w.astype(np.float32), f, first + np.concatenate([[0.0], np.cumsum(np.exp(gaps))]))


def graded(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, *, id_col: str = "doc_id", text_col: str = "text") -> tuple[list[str], list[int]]:
    """The rated sample. A toxic document has grade 0, one of low quality 1, others 2; labels with nulls are left out."""
    rated = labels.where("doc_id is not null and quality is not null and toxic is not null").select(
        F.col("doc_id").alias("q_doc"), F.when(F.col("toxic") > 0, 0).when(F.col("quality") > 0, 2).otherwise(1).alias("grade")
    )
    if not sample or not rated.limit(1).count():
        return [], []
    rated = rated.groupBy("q_doc").agg(F.min("grade").alias("grade")).orderBy(F.xxhash64("q_doc"), "q_doc").limit(sample)
    rows = docs.select(F.col(id_col).alias("q_doc"), F.col(text_col).alias("q_text")).join(F.broadcast(rated), "q_doc").groupBy("q_doc", "grade").agg(F.min("q_text").alias("q_text"))
    table = rows.select("q_doc", "q_text", "grade").toArrow().sort_by("q_doc")
    return [t or "" for t in table["q_text"].to_pylist()], table["grade"].to_pylist()


def classify(docs: DataFrame, model: Model, least: float = 0.5, *, carry: tuple[str, ...] = (), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, expected_grade, tail_probability, kept, carry...), one for each row of docs.

    kept: the probability of the top grade is `least` or more. A null text counts as empty. Repeated rows are scored
    each; an empty table gives an empty result; other columns are ignored but for those in `carry`.
    """
    schema = docs.select(*(F.col(c).alias(f"c_{c}") for c in carry)).schema

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, forms = model.words, model.forms

        def _total(found: dict[str, float]) -> float:
            return sum(found.values()) / damping(len(found) - ("" in found))

        class Weights(dict):
            def __missing__(self, token: str) -> tuple[int, float]:
                if len(self) >= REMEMBERED:
                    self.clear()
                word = normal(token)
                self[token] = pair = (word, float(words[bucket(word)]) if word else 0.0)
                return pair

        weight = Weights().__getitem__
        for batch in batches:
            scores = np.zeros(batch.num_rows)
            for i, text in enumerate(batch["q_text"].to_pylist()):
                tokens = (text or "").split()
                different = set(tokens)
                scores[i] = _total(dict(map(weight, different))) + form(text or "", tokens) @ forms
            grade, top = model.grades(scores)
            yield pa.RecordBatch.from_arrays(
                [batch["doc_id"], pa.array(grade), pa.array(top), pa.array(top >= least), *batch.columns[2:]],
                names=["doc_id", "expected_grade", "tail_probability", "kept", *batch.schema.names[2:]],
            )

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("q_text"), *(F.col(c).alias(f"c_{c}") for c in carry))
    out = "doc_id long, expected_grade double, tail_probability double, kept boolean" + "".join(f", `{x.name}` {x.dataType.simpleString()}" for x in schema)
    return rows.mapInArrow(light(scored), out).withColumnsRenamed({f"c_{c}": c for c in carry if c != "doc_id"} | ({"c_doc_id": "q_same"} if "doc_id" in carry else {})).drop("q_same")
