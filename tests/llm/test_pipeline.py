"""The corpus pipeline, stage by stage."""

from collections import Counter

import corpus_pipeline
from stratamatch.llm import packing, quality
from stratamatch.llm.queries import tokenizer_path

from .test_operators import brute_links, brute_mix, words


def test_stages_work_on_what_is_kept(spark, small, tmp_path):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, small)
        if name != "packing":
            assert tuple(out.columns) == corpus_pipeline.COLUMNS
        path = str(tmp_path / name)
        out.write.parquet(path)
        before, docs = docs, spark.read.parquet(path)
        kept[name] = docs
        if name == "quality":
            assert 0 < docs.count() <= before.count()
        if name == "near_copies":
            rows = [(r.doc_id, r.text) for r in before.collect()]
            assert {r.doc_id for r in docs.collect()} == {d for d, _, c in brute_links(rows, 5, 80) if d == c}
        if name == "passages":
            assert docs.count() == before.count()
            assert all(r.n_chars == len(r.text) for r in docs.collect())
    before = kept["passages"].collect()
    mixed = kept["mixing"].collect()
    want = brute_mix([(r.doc_id, r.source, len(words(r.text))) for r in before])
    assert Counter((r.doc_id, r.text, r.source) for r in mixed) == Counter({(r.doc_id, r.text, r.source): n for r, n in zip(before, want) if n})
    encode, tokens = packing.token_encoder(tokenizer_path()), Counter()
    for r in mixed:
        tokens[r.doc_id] += len(encode(r.text or "")) + 1
    packed, used = Counter(), Counter()
    for r in kept["packing"].collect():
        packed[r.doc_id] += r.length
        used[r.sequence_id] += r.length
    assert packed == tokens and max(used.values()) <= 2048 and sum(2048 - n for n in used.values()) <= 2048


def test_edge_rows_go_through(spark, small, tmp_path):
    from .test_operators import DOCS, EDGE

    docs = spark.createDataFrame(EDGE, DOCS)
    for name, stage in corpus_pipeline.STAGES:
        if name == "quality":
            assert quality.keep_good(docs, spark.createDataFrame([], "doc_id long, quality int")).count() == len(EDGE)
            continue
        stage(spark, docs, small).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
    assert docs.count() > 0
