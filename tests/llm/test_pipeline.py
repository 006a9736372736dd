"""The corpus pipeline, stage by stage, against brute force on the smallest tables."""

import re
from collections import Counter

import pytest

import corpus_pipeline
from joinpoisson.llm import mixing, sentencepiece_codec, toxicity

WORD = re.compile(r"[^ \t-\r]+")


def shingle_set(text):
    w = WORD.findall(text or "")
    n = min(5, len(w)) or 1
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set()


def alike(a, b):
    return len(a & b) >= 0.8 * len(a | b) if a or b else True


@pytest.fixture(scope="module")
def stages(spark, small):
    """What each stage gets and gives."""
    from joinpoisson.llm.common import cut

    docs, out = spark.read.parquet(f"{small}/documents.parquet"), []
    for name, stage in corpus_pipeline.STAGES:
        done = cut(stage(spark, docs, small), f"test-{name}")
        out.append((name, docs, done))
        docs = done
    return {name: (before, after) for name, before, after in out}


def test_order_and_columns(stages):
    assert list(stages) == ["toxicity", "exact_dedup", "near_dedup", "mix", "encode"]
    assert all(after.columns == before.columns for n, (before, after) in stages.items() if n != "encode")


def test_toxic_documents_go(spark, small, stages):
    before, after = stages["toxicity"]
    model = toxicity.train(before, spark.read.parquet(f"{small}/labels.parquet"))
    restorer = toxicity.Restorer(model.chars)
    want = {r.doc_id for r in before.collect() if model.score(model.evidence(restorer, r.text, {})) < 0.5}
    assert {r.doc_id for r in after.collect()} == want


def test_exact_copies_go(stages):
    before, after = stages["exact_dedup"]
    best = {}
    for r in before.collect():
        k = re.sub(r"[ \t-\r]", "", r.text or "")
        best[k] = min(best.get(k, (1, 0)), (-len(r.text or ""), r.doc_id))
    assert sorted(r.doc_id for r in after.collect()) == sorted(d for _, d in best.values())


def test_one_of_each_class_stays(stages):
    before, after = stages["near_dedup"]
    rows = [(r.doc_id, shingle_set(r.text)) for r in before.orderBy("doc_id").collect()]
    root = {d: d for d, _ in rows}
    for i, (a, x) in enumerate(rows):
        for b, y in rows[:i]:
            if alike(x, y):
                low, high = sorted((root[a], root[b]))
                root = {d: low if r == high else r for d, r in root.items()}
    assert sorted(r.doc_id for r in after.collect()) == sorted(set(root.values()))


def test_mix_takes_what_the_draw_says(stages):
    before, after = stages["mix"]
    want = Counter({r.doc_id: r.copies for r in mixing.digest(before).collect() if r.copies})
    assert Counter(r.doc_id for r in after.collect()) == want and max(want.values()) <= 2


def test_encoding_equals_the_library(stages):
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=sentencepiece_codec.vocabulary_path())
    before, after = stages["encode"]
    want = Counter((r.doc_id, tuple(library.encode(r.text or ""))) for r in before.collect())
    assert Counter((r.doc_id, tuple(r.ids)) for r in after.collect()) == want


def test_run_is_the_stages_together(spark, small, stages):
    got = corpus_pipeline.run(spark, small)
    assert Counter(r.doc_id for r in got.collect()) == Counter(r.doc_id for r in stages["encode"][1].collect())
