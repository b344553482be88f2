"""Neighbours on curves: small tables are cut into blocks as large ones are."""

import numpy as np
from pyspark.sql import functions as F

from stratamatch.llm import ann


def _recall(ids, m, rows):
    """(share of the true five found, share of rows a query was compared with)"""
    got, seen = {}, {}
    for r in rows:
        got.setdefault(r.query_id, set()).add(r.vec_id)
        seen[r.query_id] = r.rows_seen
    hits = []
    for q in ids[ids % 50 == 0]:
        s = ann.cosine(m[ids == q][0], m)
        s[ids == q] = -2
        hits.append(len(got[q] & set(ids[np.argsort(-s)[:5]].tolist())) / 5)
    return np.mean(hits), np.mean(list(seen.values())) / len(ids)


def test_layout_has_no_switch_by_size():
    blocks = [ann.layout(n)[0] for n in range(1, 10_000)]
    assert all(0 <= b - a <= 1 for a, b in zip(blocks, blocks[1:])) and blocks[499] == 15 and blocks[1999] == 62 and blocks[-1] == 128
    assert ann.layout(10**7) == (1221, 14) and all(ann.layout(n)[1] <= 1 for n in range(1, 10**6, 997))


def test_recall_on_the_given_vectors(spark):
    e = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    ids, m = (np.array(x) for x in zip(*((r.vec_id, np.array(r.embedding, dtype=float)) for r in e.select("vec_id", "embedding").collect())))
    assert ann.layout(len(ids)) == (62, 1)
    found, seen = _recall(ids, m, ann.nearest(e, F.col("vec_id") % 50 == 0).collect())
    few, looked = _recall(ids, m, ann.nearest(e, F.col("vec_id") % 50 == 0, curves=8).collect())
    print("recall", found, seen, few, looked)
    assert found >= 0.9 and seen < 0.85
    assert few > 1.5 * looked  # random blocks of as many rows hold a share of the neighbours equal to their share of rows


def test_recall_on_a_table_of_many_chunks(spark):
    """20,000 rows near 400 centres: few curves suffice, and a query looks at a small part of the rows."""
    rng = np.random.default_rng(3)
    centres = rng.normal(size=(400, 64))
    m = centres[rng.integers(0, 400, 20_000)] + 0.35 * rng.normal(size=(20_000, 64))
    ids = np.arange(20_000)
    df = spark.createDataFrame([(int(i), x.tolist()) for i, x in zip(ids, m)], "vec_id long, embedding array<double>")
    found, seen = _recall(ids, m, ann.nearest(df, F.col("vec_id") % 50 == 0, curves=12).collect())
    print("recall", found, seen)
    assert found >= 0.9 and seen < 0.25
