"""Quality classifier: probability that a whole text is of quality 1, learnt from labelled rows of the kept folds.

See classify for the model and for what nulls, empty texts and unlabelled tables give.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import classify

FOLDS, FOLD = 3, 1


def fit(docs: DataFrame, labels: DataFrame, rows: int = classify.SAMPLE_ROWS) -> classify.Model:
    """Fits on at most `rows` labelled documents outside the held-out fold."""
    known = labels.select("doc_id", F.col("quality").cast("int").alias("y")).where(~classify.held_out("doc_id", FOLDS, FOLD))
    return classify.fitted(classify.sampled(docs, known, rows), lambda texts, labels: (classify.train(texts, labels), 0.0))[0]


def score(docs: DataFrame, model: classify.Model) -> DataFrame:
    """Rows (doc_id, held_out, score, predicted) for every row of docs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = model.scores(batch.column(2))
            one = model.classes.index(1) if 1 in model.classes else None
            score = p[:, one] if one is not None else np.full(batch.num_rows, 0.5 if not model.classes else 0.0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", classify.held_out("doc_id", FOLDS, FOLD).alias("held_out"), F.col("text").cast("string")).mapInArrow(run, f"doc_id {kind}, held_out boolean, score double, predicted int")
