"""Language identification with calibrated rejection.

The classifier is that of classify, fitted on a bounded sample of rows with a language. Rejection: on sampled rows kept
from the fit, the threshold is the score below which a share of REJECT of correctly named texts falls, yet no less than
MARGIN times what a guess among the classes scores; a text scoring less, or without any letter, is rejected. Texts of
languages not learnt score near a guess, since their n-grams say nothing. See classify for nulls and empty tables.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import classify

FOLDS, FOLD = 4, 2
UNDETERMINED = "und"
#: Share of rightly named calibration texts that may be rejected, and the least threshold in guesses (1 / classes).
REJECT, MARGIN = 0.001, 1.4


def fit(docs: DataFrame, rows: int = classify.SAMPLE_ROWS) -> tuple[classify.Model, float]:
    """(model, rejection threshold), from at most `rows` rows outside the held-out fold."""
    return classify.fitted(classify.sampled(docs.where(~classify.held_out("doc_id", FOLDS, FOLD)), "lang", rows), _calibrated)


def _calibrated(texts: list[str], labels: list) -> tuple[classify.Model, float]:
    """The model of four fifths of the texts, and the threshold by the rest."""
    lettered = [i for i, t in enumerate(texts) if classify.has_letter(t)]
    texts, labels = [texts[i] for i in lettered], [labels[i] for i in lettered]
    # Sorted texts would put like with like.
    order = np.random.default_rng(1).permutation(len(texts))
    texts, labels = [texts[i] for i in order], [labels[i] for i in order]
    cut = len(texts) - len(texts) // 5
    model = classify.train(texts[:cut], labels[:cut])
    p = model.scores(pa.array(texts[cut:], pa.string()))
    right = [row.max() for row, y in zip(p, labels[cut:]) if model.classes[int(row.argmax())] == y]
    least = MARGIN / len(model.classes) if len(model.classes) > 1 else 0.0
    return model, max(least, float(np.quantile(right, REJECT, method="lower"))) if right else 0.0


def _named(model: classify.Model, threshold: float, texts: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(language, score, rejected) of each text."""
    n = len(texts)
    p = model.scores(texts) if model.classes else np.zeros((n, 1))
    best = p.argmax(axis=1)
    score = p[np.arange(n), best]
    names = [model.classes[b] if model.classes else UNDETERMINED for b in best]
    for i, text in enumerate(texts.to_pylist()):
        # Most texts begin with a letter, which settles it.
        if not (text and (text[0].isalpha() or classify.has_letter(text))):
            names[i], score[i] = UNDETERMINED, 0.0
    return names, score, np.array([x == UNDETERMINED for x in names], bool) | (score < threshold)


def predict(docs: DataFrame, model: classify.Model, threshold: float = 0.0) -> DataFrame:
    """Rows (doc_id, held_out, lang_pred, score, rejected) for every row of docs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, score, rejected = _named(model, threshold, batch.column(2))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(names, pa.string()), pa.array(score), pa.array(rejected)], ["doc_id", "held_out", "lang_pred", "score", "rejected"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", classify.held_out("doc_id", FOLDS, FOLD).alias("held_out"), F.col("text").cast("string")).mapInArrow(run, f"doc_id {kind}, held_out boolean, lang_pred string, score double, rejected boolean")


def accepted(docs: DataFrame, model: classify.Model, threshold: float) -> DataFrame:
    """The rows of docs that are not rejected, with the columns of docs."""
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(~_named(model, threshold, batch.column(at))[2]))

    return docs.mapInArrow(run, docs.schema)
