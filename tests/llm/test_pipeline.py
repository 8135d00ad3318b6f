"""The pipeline on the smallest tables: every stage against what it should have kept."""

import collections
import hashlib
import random

import numpy as np

import corpus_pipeline
from blockbwt.llm import byte_bpe

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    import public_tokenizers

    docs = corpus_pipeline.common.table(spark, SF, "documents")
    found = []
    for _, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.common.materialise(stage(spark, docs, SF), "test-stage")
        found.append(docs.collect())
    lang, near, mixed, encoded = found
    assert len(lang) == 200 and {x.lang for x in lang} <= {"en", "fr", "de", "es"}
    from test_operators import brute_components

    want = {i for i, _, _, kept in brute_components([(x.doc_id, x.text) for x in lang]) if kept}
    assert {x.doc_id for x in near} == want
    words = sum(len(x.text.split()) for x in near)
    assert abs(sum(len(x.text.split()) for x in mixed) - 1.5 * words) <= 40
    enc = byte_bpe.encoding(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    sha = lambda x: hashlib.sha256(x).hexdigest()
    assert collections.Counter((x.doc_id, x.ids_sha256, x.decoded_sha256) for x in encoded) == collections.Counter((x.doc_id, sha(np.array(enc.encode_ordinary(x.text), "<u4").tobytes()), sha(x.text.encode())) for x in mixed)


ODD = "doc_id long, text string, lang string, source string, n_chars long, node string, key string, size long, region long, h long"


def test_odd_rows_pass_every_stage(spark, tmp_path):
    """Nulls in every column, repeated rows and ids, ties, a very long text and clashing columns, with and without anything to learn from."""
    rng = random.Random(21)
    bags = {"en": "the of and is that this with for are on".split(), "de": "der die und nicht auf mit ist das ein zu".split()}
    say = lambda g, n: " ".join(rng.choice(bags[g]) for _ in range(n))
    rows = [(i, say(g, rng.randrange(20, 60)), g, rng.choice(["a", "b", None])) for i, g in ((i, rng.choice(["en", "de"])) for i in range(120))]
    one = rows[5]
    rows += [one, one, (5, say("en", 30), "en", "a"), (None, say("en", 40), None, None), (None, say("de", 40), "de", None), (None, None, None, None)]
    rows += [(900, None, "en", "a"), (901, "", "en", "b"), (902, " \n ", "de", None), (903, "123 -- 4", "en", "a"), (904, say("en", 40_000), "en", "long"), (905, "日本語" * 50, None, "a")]
    frame = spark.createDataFrame([(*x, 0, "n", "k", 1, 2, 3) for x in rows], ODD).repartition(5)
    frame.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(0, 1), (1, 0), (1, 1), (None, 1)], "doc_id long, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    kept = [("language ID", frame)]
    docs = frame
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.common.materialise(stage(spark, docs, str(tmp_path)), "odd")
        kept.append((name, docs))
    lang, near, mixed, encoded = (x.collect() for _, x in kept[1:])
    want = collections.Counter((i, t) for i, t, _, _ in rows if i not in (900, 901, 902, 903, 905) and t is not None)
    assert collections.Counter((x.doc_id, x.text) for x in lang) == want
    assert all(x.lang in bags for x in lang)
    from test_operators import brute_components

    # of each group one text: that of the least id; groups of null ids alone keep one of them
    assert len({(x.doc_id, x.text) for x in near}) == len(near)
    named = {i for i, _, _, is_kept in brute_components([(x.doc_id, x.text) for x in lang]).elements() if is_kept and i is not None}
    assert {x.doc_id for x in near if x.doc_id is not None} == named
    assert sum(x.doc_id is None for x in near) == 2 and any(x.doc_id == 904 for x in near)
    words = collections.Counter()
    for x in near:
        words[x.source] += len(x.text.split())
    taken = collections.Counter()
    for x in mixed:
        taken[x.source] += len(x.text.split())
    assert abs(sum(taken.values()) - 1.5 * sum(words.values())) <= len(words) and all(taken[s] <= 2 * words[s] + 1 for s in words)
    assert None in taken and all(x.n_chars == len(x.text) for x in mixed)
    assert len(encoded) == len(mixed) and set(corpus_pipeline.COLUMNS) == set(kept[3][1].columns)


def test_without_anything_to_learn_from(spark):
    frame = spark.createDataFrame([(1, "some words in it", None, "a", 0), (2, None, None, None, None)], "doc_id long, text string, lang string, source string, n_chars long")
    assert corpus_pipeline.identify_language(spark, frame, SF).count() == 0


def test_empty_documents(spark):
    docs = corpus_pipeline.common.table(spark, SF, "documents").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.common.materialise(stage(spark, docs, SF), "test-empty")
        assert docs.count() == 0
