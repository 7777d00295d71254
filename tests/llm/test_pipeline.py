"""The pipeline's stages keep the documents' columns and take effect."""

from cellbalance.llm import common

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    import corpus_pipeline

    docs = common.documents(spark, SF)
    columns, before = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = common.table(stage(spark, docs, SF), f"test-{name}")
        assert docs.columns == columns
        assert 0 < docs.count() <= before
        before = docs.count()
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert pieces.select("doc_id").distinct().count() == docs.select("doc_id").distinct().count()


def test_lines_of_large_blocks(spark):
    """Pairs of lines whose only common block holds 400 others."""
    import random

    import corpus_pipeline

    rng = random.Random(29)
    word = lambda: "".join(rng.choices("bcdfghjklmnpqrstvwxz", k=11))
    pairs = [(word(), word()) for _ in range(200)]
    texts = [f"alpha beta {x} {y}" for p in pairs for x, y in (p, [w[:5] + "a" + w[6:] for w in p])]
    docs = spark.createDataFrame([(i, t, "en", "here", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    kept = {r["doc_id"] for r in corpus_pipeline.lines(spark, docs, SF).filter("text <> ''").collect()}
    assert kept == set(range(0, 400, 2))
