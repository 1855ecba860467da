"""The pipeline against its operators applied one by one in plain Python."""

from fractions import Fraction

import pytest

pytest.importorskip("public_tokenizers")

import corpus_pipeline  # noqa: E402
from cardest.llm import mixing, ngrams, toxicity  # noqa: E402


def test_pipeline(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = toxicity.fit(docs, labels)
    restorer = toxicity.Restorer(model.language)
    clean = [r for r in docs.collect() if model.score(restorer.words(r["text"])) < 0.3]
    first = {}
    for r in sorted(clean, key=lambda r: r["doc_id"]):
        first.setdefault(" ".join((r["text"] or "").split()), r)
    unique = list(first.values())
    df = spark.createDataFrame(unique, docs.schema)
    classes = {r["doc_id"]: r["component_id"] for r in ngrams.near_copies(df, 5, Fraction(4, 5)).collect()}
    left = [r for r in unique if classes[r["doc_id"]] == r["doc_id"]]
    copies = {r["doc_id"]: r["copies"] for r in mixing.mix(spark.createDataFrame(left, docs.schema)).collect()}
    got = corpus_pipeline.run(spark, sf_dir).collect()
    seen = {}
    for r in got:
        if r["start"] == 0:
            seen[r["doc_id"]] = seen.get(r["doc_id"], 0) + 1
    assert seen == {i: n for i, n in copies.items() if n}
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "exact dedup", "n-gram Jaccard join", "mixing sources to target weights", "packing"]


def test_copies_without_identifier_go(spark):
    words = [f"w{i}" for i in range(40)]
    near = " ".join(words + ["x"])
    rows = [(1, " ".join(words)), (2, "another text of its own, kept as it is"), (None, " ".join(words))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(r["doc_id"] for r in corpus_pipeline.exact_dedup(spark, docs, "").collect()) == [1, 2]
    rows[2] = (None, near)
    rows += [(None, "a text without identifier that is a copy of nothing"), (None, None)]
    left = corpus_pipeline.ngram_jaccard_join(spark, spark.createDataFrame(rows, "doc_id long, text string"), "").collect()
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in left) == sorted((i or 0, t or "") for i, t in rows if t != near)
