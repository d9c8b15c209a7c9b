"""Topics are fitted on every row: rows that a sample of a few thousand would hardly meet move the centres."""

import numpy as np
from pyspark.sql import functions as F

from quotaknn.llm import mixing


def test_every_text_counts(spark):
    rng = np.random.default_rng(1)
    raw = [np.abs(rng.standard_normal(mixing.BUCKETS)) for _ in range(40)] + [None]
    x = [None if v is None else np.rint(v / np.linalg.norm(v) * mixing.UNIT).astype("<u2") for v in raw]
    made = [(None if v is None else bytearray(v.tobytes()),) for v in x]
    rows = spark.createDataFrame(made * 3, "p binary")
    sums, n = mixing.means(rows, F.col("p"))
    whole = np.array([v for v in x if v is not None], np.int64)
    assert n.tolist() == [120] and (sums[0] == 3 * whole.sum(0)).all() and (sums[1:] == 3 * whole.T @ whole).all()
    c = mixing.fit_topics(rows, F.col("p"), 4)
    assert (c == mixing.fit_topics(rows.repartition(7), F.col("p"), 4)).all() and len(c) == 4
    sums, n = mixing.means(rows, F.col("p"), c)
    assert n.sum() == 120 and (sums.sum(0) == 3 * whole.sum(0)).all()
