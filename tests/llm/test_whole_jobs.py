"""What a cut would leave out: each test holds input that only the whole job reads."""

import collections
import random
import textwrap

import pytest
import corpus_pipeline
from blockbwt.llm import common, language_id, license_scan, merkle

SF = "/root/testdata/sf0.001"


def test_language_id_learns_beyond_any_prefix(spark):
    rng = random.Random(8)
    bags = {"en": "the of and is that this with for are on".split(), "de": "der die und nicht auf mit ist das ein zu".split()}
    same = "0123456789 " * 500  # of 5,500 characters, alike in both languages
    rows = [(i, same + " ".join(rng.choice(bags[g]) for _ in range(400)), g) for i, g in enumerate(rng.choice(list(bags)) for _ in range(300))]
    model = language_id.learn(spark.createDataFrame(rows[:200], "doc_id long, text string, lang string"))
    got = {x.doc_id: x for x in language_id.predict(spark.createDataFrame(rows[200:], "doc_id long, text string, lang string"), model).collect()}
    assert sum(got[i].lang_pred == g for i, _, g in rows[200:]) >= 98
    # the temperature is fitted on what's predicted: scores are as sure as they are right
    assert sum(x.score for x in got.values()) / len(got) > 0.9


def test_pipeline_takes_rows_with_null_and_repeated_ids(spark):
    rng = random.Random(3)
    words = [f"w{i}" for i in range(5000)]
    text = lambda: " ".join(rng.choice(words) for _ in range(40))
    twice, other = text(), text()
    # null ids, a repeated row, one id on three texts, and a group of null ids alone
    rows = [(None, text()) for _ in range(5)] + [(7, twice)] * 4 + [(8, text()) for _ in range(3)] + [(None, other)] * 3 + [(i, text()) for i in range(20, 40)]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long").repartition(4)
    near = common.materialise(corpus_pipeline.drop_near_duplicates(spark, docs, SF), "near")
    assert collections.Counter((x.doc_id, x.text) for x in near.collect()) == dict.fromkeys(set(rows), 1)
    for stage in (near, docs):
        before = collections.Counter((x.doc_id, x.text) for x in stage.collect())
        got = corpus_pipeline.mix_sources(spark, stage, SF).collect()
        # one source: 1.5 times its size, whole copies of each row twice at most, and one cut
        assert sum(len(x.text.split()) for x in got) == 60 * sum(before.values())
        after = collections.Counter((x.doc_id, x.text) for x in got if len(x.text.split()) == 40)
        assert all(before[k] <= after[k] <= 2 * before[k] for k in before)


@pytest.mark.parametrize("mark", ["# ", " * ", "// ", "-- ", "| "])
def test_license_headers_in_comments(mark):
    library, hashes = license_scan.Library(license_scan.TEMPLATES), license_scan._Hashes()
    for name in ("mit", "gpl-3.0", "apache-2.0", "bsd-2-clause", "isc"):
        header = "\n".join(mark + x for x in textwrap.wrap(license_scan.TEMPLATES[name], 72))
        found = license_scan.scan_texts([f"{mark}\n{mark}\n{header}\nx = 1\n"], library, hashes)
        # the first word is counted among all words, comment marks too
        assert [x for x in found if x[1] == name] == [(0, name, 1.0, 3)]


def test_merkle_cuts_any_script(spark):
    from pyspark.sql import functions as F

    rng = random.Random(6)
    pick = lambda letters, n: "".join(rng.choice(letters) for _ in range(n))
    kinds = {
        "capitals": lambda: " ".join(pick("ABCDEFGHIJ", rng.randrange(2, 9)) for _ in range(300)),
        "cyrillic": lambda: " ".join(pick("абвгдежзик", rng.randrange(2, 9)) for _ in range(300)),
        "tabular": lambda: "\t".join(str(rng.randrange(10**5)) for _ in range(300)),
        "symbols": lambda: " ".join(pick("abcdefgh", 4) + rng.choice(";)!") for _ in range(300)),
        "ideographs": lambda: pick([chr(0x4E00 + i) for i in range(2000)], 1500),
        "four letters, unbroken": lambda: pick("ACGT", 1500),
        "alike": lambda: "A " * 700 + pick("xyz", 5),
        "one letter": lambda: "A" * 3000 + pick("xyz", 5),
    }
    rows = [(k, x, x[: len(x) - len(x) // 3] + f()[: len(x) // 3], x[:40] + "@" + x[40:]) for k, f in kinds.items() for x in [f()]]
    df = spark.createDataFrame(rows, "kind string, a string, b string, c string")
    leaf = lambda c: merkle.leaves(F.col(c))
    got = {x.kind: x for x in df.select("kind", F.size(leaf("a")).alias("n"), merkle.likeness(merkle.sketch(leaf("a")), merkle.sketch(leaf("b"))).alias("third"), merkle.likeness(merkle.sketch(leaf("a")), merkle.sketch(leaf("c"))).alias("one")).collect()}
    for kind, x in got.items():
        assert x.n >= 10, (kind, x)
        if kind not in ("alike", "one letter"):
            assert x.third >= 0.35 and x.one >= 0.85, (kind, x)
