import public_tokenizers as P
from tokenizers import Tokenizer

import corpus_pipeline
from calib.llm import rules, weak_labels
from test_operators import ODD, brute_groups, check_packing


def test_stages_one_by_one(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    good = {r.doc_id for r in weak_labels.judge(docs).where("kept").collect()}
    texts = {r.doc_id: r.text for r in docs.collect()}
    one = corpus_pipeline.quality_classifier(spark, docs, sf)
    assert one.columns == docs.columns and {r.doc_id for r in one.collect()} == good
    two = corpus_pipeline.quality_rules(spark, one, sf)
    assert two.columns == docs.columns and {r.doc_id for r in two.collect()} == {r.doc_id for r in rules.judge(one).where("kept").collect()}
    left = [(r.doc_id, r.text) for r in two.collect()]
    groups = brute_groups(left)
    three = corpus_pipeline.near_duplicates(spark, two, sf)
    kept = {r.doc_id for r in three.collect()}
    assert three.columns == docs.columns and kept == {i for i, (_, c) in groups.items() if i == c}
    tok = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    rows = corpus_pipeline.run(spark, sf).collect()
    assert {r.doc_id for r in rows} == kept
    check_packing(rows, {i: [tok.encode(texts[i], add_special_tokens=False).ids + [2]] for i in kept})


def test_stages_take_odd_documents(spark, sf):
    """Nulls, repeated rows, columns whose names clash with those that stages make, and an empty table."""
    kinds = "doc_id long, text string, lang string, source string, n_chars long, votes string, component_id long, _c string"
    clean = "The river runs to the sea and the hill is green in the morning while people of the town walk on an old road with a dog that likes rain"
    odd = spark.createDataFrame([(i, t, None, "s", None, "+", 1, "c") for i, t in [*ODD, (21, clean), (20, clean)]], kinds)
    left = []
    for frame in (odd, odd.where("1 = 0")):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, frame, sf)
            assert name == corpus_pipeline.STAGES[-1][0] or out.columns == frame.columns
            frame = spark.createDataFrame(out.collect(), out.schema)
        left.append([r.doc_id for r in frame.collect()])
    assert left == [[20], []]
