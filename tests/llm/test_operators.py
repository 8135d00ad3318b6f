"""Each operator against brute force on a small fixture with nulls, empty and long texts, ties, repeats and clashing columns."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import public_tokenizers
import pytest

from blockbwt.llm import brown_lm, byte_bpe, chat_format, common, cover_tree, elias_fano, language_id, license_scan, lsh_forest, merkle, mixing, token_output

JSON, RANKS = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")
WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, node string, size long, part int, key string"


def fixture_rows():
    rng = random.Random(5)
    words = ["the", "of", "Und", "der", "é", "naïve", "<|endoftext|>", "x1", "don't", "日本語", "a b", "--", "1234"]
    texts = [None, "", " ", "  two  spaces ", "\n\nlines\n \n", "a", "a b c d", "A B C D", "a b c d e", "tab\tand\rcr", " em\u0085nel\x1cfs"]
    for _ in range(30):
        texts.append(rng.choice([" ", "  ", "\n"]).join(rng.choice(words) for _ in range(rng.randrange(1, 60))))
    texts.append("long " * 30_000 + "word" * 5_000)
    texts += [texts[12], texts[12], texts[13] + " extra"]
    out = [(i * 3 - 6, t, rng.choice(["en", "fr", None]), rng.choice(["s1", "s2", None]), 0) for i, t in enumerate(texts)]
    return [x + ("n", 9, 9, "k") for x in out]


@pytest.fixture(scope="module")
def docs(spark):
    rows = fixture_rows()
    return spark.createDataFrame(rows + [rows[15], (None, "no id at all", "en", "s1", 0, "n", 9, 9, "k"), (None, None, None, None, None, None, None, None, None)], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def test_elias_fano():
    rng = np.random.default_rng(1)
    for n, top in ((0, 1), (1, 5), (10, 3), (1000, 10), (1000, 10**12), (3000, 3000)):
        v = np.sort(rng.integers(-5, top, n))
        e = elias_fano.EliasFano.from_bytes(elias_fano.EliasFano.encode(v).to_bytes())
        assert (e.all() == v).all()
        assert all(e.select(i) == v[i] for i in range(0, n, 7))
        assert all(e.rank(x) == np.searchsorted(v, x) for x in (-6, -5, 0, 3, top // 2, top))
    with pytest.raises(ValueError):
        elias_fano.EliasFano.encode(np.array([2, 1]))
    wide = elias_fano.EliasFano.encode(np.arange(0, 10**7, 1000)).to_bytes()
    assert len(wide) < 10**4 * 2


def test_token_output(spark, docs, none, tmp_path):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(JSON)  # as the library has it, "<|endoftext|>" in a text included
    token_output.write_segments(docs, str(tmp_path / "t"), JSON, segment_tokens=300)
    got = [tuple(x) for x in token_output.read_documents(spark, str(tmp_path / "t")).collect()]
    from pyspark.sql import functions as F

    rows = sorted(((x.doc_id, x.text, x.h) for x in docs.withColumn("h", F.xxhash64("text")).collect()), key=lambda x: (x[0] is not None, x[0], x[2], x[1] or ""))
    rows = [x[:2] for x in rows]
    want, at = [], 0
    for i, t in rows:
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        want.append((i, at, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    key = lambda x: x[1]
    assert sorted(got, key=key) == want
    segments = token_output.read_segments(spark, str(tmp_path / "t")).collect()
    assert len(segments) > 3
    one = max(segments, key=lambda x: x.n_docs)
    assert len(token_output.document_ids(one.asDict(), 0)) >= 1
    assert any(50256 in tok.encode(t or "", add_special_tokens=False).ids for _, t in rows)  # the case occurs
    twice = collections.Counter(i for i, _ in rows if i is not None)
    some = [i for i in sorted(twice) if i % 4 == 0 or twice[i] > 1]
    found = token_output.find_documents(spark, str(tmp_path / "t"), [*some, 10**9]).collect()
    assert sorted((x.doc_id, x.start, zlib.crc32(np.array(x.ids, "<u4").tobytes())) for x in found) == sorted((i, a, c) for i, a, _, c in want if i in some)
    for s in segments:
        x = s.asDict()
        ends = np.cumsum([len(token_output.document_ids(x, i)) for i in range(s.n_docs)])
        assert all(token_output.document_at(x, o) == np.searchsorted(ends, o, side="right") for o in range(0, s.n_tokens, 11))
    token_output.write_segments(docs, str(tmp_path / "s"), JSON, special_as_text=True)
    assert 50256 not in {i for x in token_output.find_documents(spark, str(tmp_path / "s"), some).collect() for i in x.ids}
    token_output.write_segments(none, str(tmp_path / "e"), JSON)
    assert token_output.read_documents(spark, str(tmp_path / "e")).count() == 0


def test_byte_bpe(spark, docs, none):
    enc = byte_bpe.encoding(RANKS, public_tokenizers.PATTERN)
    encoded = common.materialise(byte_bpe.encode(docs, RANKS, public_tokenizers.PATTERN, chunk_chars=200), "encoded")
    tokens = byte_bpe.token_table(spark, RANKS)
    done = byte_bpe.decode(encoded, tokens)
    got = sorted((str(x.doc_id), bytes(x.ids), bytes(x.decoded)) for x in done.collect())
    assert got == sorted((str(x.doc_id), np.array(enc.encode_ordinary(x.text or ""), "<u4").tobytes(), (x.text or "").encode()) for x in docs.collect())
    # a table too large for a broadcast
    again = byte_bpe.decode(encoded, tokens, most_tokens=10).collect()
    assert got == sorted((str(x.doc_id), bytes(x.ids), bytes(x.decoded)) for x in again)
    odd = spark.createDataFrame([(1, None), (2, b""), (3, np.array([7, 10**6, 8], "<u4").tobytes())], "doc_id long, ids binary")
    for most in (byte_bpe.MOST_TOKENS, 10):
        found = {x.doc_id: x.decoded for x in byte_bpe.decode(odd, tokens, most_tokens=most).collect()}
        assert found[1] is None and bytes(found[2]) == b"" and bytes(found[3]) == enc.decode_bytes([7, 8])
    assert byte_bpe.encode(none, RANKS, public_tokenizers.PATTERN).count() == 0


def test_byte_bpe_chunks_are_shuffled_once(docs):
    plan = byte_bpe.encode(docs, RANKS, public_tokenizers.PATTERN)
    plan.collect()
    assert "ReusedExchange" in plan._jdf.queryExecution().executedPlan().toString()


def test_brown_lm(spark, docs, none):
    from pyspark.sql import functions as F

    held = language_id.remainder(F.col("doc_id"), 7) == 2
    got = brown_lm.score(docs, held, classes=6, chunk_chars=300).collect()
    rows = docs.collect()
    tokens = lambda t: [w.lower() if w.isascii() else re.sub("[A-Z]", lambda m: m[0].lower(), w) for w in WORD.findall(t or "")] + [" "]
    out = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 7 == 2
    c = collections.Counter(w for x in rows if not out(x.doc_id) for w in tokens(x.text))
    n, v = sum(c.values()), len(c)
    want = collections.Counter()
    for x in rows:
        t = tokens(x.text)
        want[(x.doc_id, out(x.doc_id), len(t), sum(w in c for w in t), n, round(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in t), 5))] += 1
    assert collections.Counter((x.doc_id, x.held_out, x.n_tokens, x.n_known, x.train_tokens, round(x.base_score, 5)) for x in got) == want
    assert all(x.score < 0 and math.isfinite(x.score) for x in got)
    assert brown_lm.score(none, held).count() == 0


def test_brown_probabilities_sum_to_one():
    pairs = np.array([[0.0, 3, 2], [2, 1, 4], [3, 0, 1]])
    m = brown_lm.Smoothed(pairs, np.array([1.0, 2, 0]), np.array([3.0, 4, 7]))
    total = (10**m.step).sum(1) + 10**m.unknown
    assert np.allclose(total, 1)


def sparse(rows):
    rows = np.asarray(rows)
    at = np.argwhere(rows)
    return (rows > 0).sum(1), at[:, 1], rows[at[:, 0], at[:, 1]]


def test_exchange_finds_planted_classes():
    rng = np.random.default_rng(3)
    rows = np.array([rng.multinomial(200, [0.45, 0.45, 0.05, 0.05] if i % 2 else [0.05, 0.05, 0.45, 0.45]) for i in range(20)])
    table, total = rows[:2].astype(float), rows[:2].sum(1).astype(float)
    of = brown_lm.exchange(*sparse(rows), np.array([0, 1] + [-1] * 18), table, total, 1, share=0)
    assert len(set(of[::2])) == 1 and len(set(of[1::2])) == 1 and of[0] != of[1]
    assert (table == [rows[of == c].sum(0) for c in (0, 1)]).all() and (total == table.sum(1)).all()


def test_exchange_gains_are_exact():
    """Each word's move against the criterion computed anew for every class; and no pass lowers it."""
    rng = np.random.default_rng(4)
    rows, k = rng.poisson(0.8, (30, 12)), 5
    rows[7] = 0
    own = rng.integers(0, k, 30)
    own[3] = -2
    counts = lambda of: (np.array([rows[of == c].sum(0) for c in range(k)], float), np.array([rows[of == c].sum() / 2 for c in range(k)]))
    rows[3] = 0  # a word that stays out isn't in the counts
    want, order = own.copy(), np.argsort(-rows.sum(1) / 2, kind="stable")
    for i in order:
        if rows[i].any():
            scores = []
            for c in range(k):
                trial = want.copy()
                trial[i] = c
                scores.append(brown_lm.criterion(*counts(trial), 2))
            if max(scores) > scores[want[i]] + 1e-9:
                want[i] = int(np.argmax(scores))
    table, total = counts(own)
    before = brown_lm.criterion(table, total, 2)
    got = brown_lm.exchange(*sparse(rows), own, table, total, 2, share=0)
    assert (got == want).all() and brown_lm.criterion(table, total, 2) > before
    assert np.allclose(table, counts(got)[0]) and np.allclose(total, counts(got)[1])


def test_brown_scores_from_classes_and_counts(spark, docs):
    """Scores recomputed in plain Python from the words' classes; classes cover the whole vocabulary."""
    from pyspark.sql import functions as F

    rng = random.Random(12)
    bags = ["red green blue grey pink".split(), "runs eats sleeps sings".split(), "dog cat cow hen".split()]
    texts = [" ".join(w for _ in range(rng.randrange(1, 9)) for w in (rng.choice(bags[0]), rng.choice(bags[2]), rng.choice(bags[1]))) for _ in range(150)]
    more = spark.createDataFrame([(1000 + i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    every = docs.select("doc_id", "text").unionByName(more)
    held = language_id.remainder(F.col("doc_id"), 7) == 2
    learned, scored = brown_lm.learn_and_score(every, held, classes=6, chunk_chars=400)
    got = scored.collect()
    known = {bytes(x.word): (x.n, x["class"]) for x in brown_lm.word_classes(learned).collect()}
    out = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 7 == 2
    rows = [(x.doc_id, [*(x.text or "").encode().lower().split(), b" "]) for x in every.collect()]
    n = collections.Counter(w for i, t in rows if not out(i) for w in t)
    assert {w: c for w, (c, _) in known.items()} == n
    assert all((of == 0) == (w == b" ") for w, (_, of) in known.items())
    pairs, once, mass = np.zeros((7, 7)), np.zeros(7), np.zeros(7)
    for i, t in rows:
        if not out(i):
            for a, b in zip([b" ", *t], t):
                pairs[known[a][1], known[b][1]] += 1
                once[known[a][1]] += n[b] == 1
                mass[known[b][1]] += 1
    assert (learned.class_tokens == mass).all()
    model = brown_lm.Smoothed(pairs, once, mass)
    want = collections.Counter()
    for i, t in rows:
        total, before = 0.0, 0
        for w in t:
            of = known[w][1] if w in known else 7
            total += model.unknown[before] if of == 7 else model.step[before, of] + math.log10(n[w] / mass[of])
            before = of
        want[(i, len(t), round(total, 6))] += 1
    assert collections.Counter((x.doc_id, x.n_tokens, round(x.score, 6)) for x in got) == want
    # both sides' criterion is that of the class bigrams, and rose
    words = pairs.copy()
    now = brown_lm.criterion(np.hstack([words.T[1:], words[1:]]), words.sum(0)[1:], 2)
    assert learned.criteria[0] <= learned.criteria[1] + 1e-6 <= now + 2e-6
    # unlike words of one kind share a class
    of = [[known[w.encode()][1] for w in bag] for bag in bags]
    assert all(len(set(x)) <= 2 for x in of) and not set(of[0]) & set(of[1])
    held_out = [x for x in got if x.held_out and x.doc_id is not None and x.doc_id >= 1000]
    assert sum(x.score for x in held_out) > sum(x.base_score for x in held_out)


def brute_top(rows, k):
    v = {(i, tuple(math.floor(64 * float(x)) for x in e)) for i, e in rows if i is not None and e and all(x is not None and math.isfinite(x) for x in e)}
    out = set()
    for q in {i for i, _ in v if i % 20 == 0}:
        found = sorted((-sum(a * b for a, b in zip(x, e)), i) for own, x in v if own == q for i, e in v if i != q and len(e) == len(x))[:k]
        out |= {(q, r + 1, i, -s) for r, (s, i) in enumerate(found)}
    return out


def test_cover_tree(spark):
    from pyspark.sql import functions as F

    rng = np.random.default_rng(8)
    rows = [(i, rng.normal(size=6).astype(np.float32).tolist()) for i in range(400)]
    rows += [(i, rows[7][1]) for i in range(400, 700)]  # ties
    rows += [(None, [1.0] * 6), (701, None), (702, []), (703, [1.0, None] * 3), (704, [float("nan")] * 6), (705, [float("inf")] * 6), (720, [1.0] * 3), (721, [2.0] * 3), rows[3]]
    df = spark.createDataFrame([(i, e, 1, 2) for i, e in rows], "vec_id long, embedding array<float>, label int, block long")
    got = cover_tree.top_k(df, F.col("vec_id") % 20 == 0, block=64)
    assert {tuple(x) for x in got.collect()} == brute_top(rows, 20)
    # ids that repeat with other vectors, as query and as candidate; repeated rows count once
    more = rows[:200] + [(i, rng.normal(size=6).astype(np.float32).tolist()) for i in (20, 40, 41, 42)] + rows[15:25]
    df = spark.createDataFrame(more, "vec_id long, embedding array<float>")
    assert {tuple(x) for x in cover_tree.top_k(df, F.col("vec_id") % 20 == 0, block=64).collect()} == brute_top(more, 20)
    assert cover_tree.top_k(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0


def test_cover_tree_scores_beyond_doubles(spark, monkeypatch):
    from pyspark.sql import functions as F

    monkeypatch.setattr(cover_tree, "ASKING", 2)
    rng = np.random.default_rng(18)
    rows = [(i, rng.uniform(-1.2e6, 1.2e6, 20).tolist()) for i in range(300)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = cover_tree.top_k(df, F.col("vec_id") % 20 == 0, block=64).collect()
    assert {tuple(x) for x in got} == brute_top(rows, 20) and max(x.score for x in got) > 1 << 53
    with pytest.raises(OverflowError):
        cover_tree.products(np.full((1, 2), 1 << 40), np.full((1, 2), 1 << 40))


def test_cover_tree_equals_its_sql(spark, tmp_path):
    import duckdb

    rng = np.random.default_rng(19)
    rows = [(i, rng.normal(size=4).tolist()) for i in [*range(100), 20, 20, 33]] + [(7, None), (8, [1.0, None, 2.0, 3.0]), (5, [0.5] * 4), (5, [0.5] * 4)]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>").write.parquet(str(tmp_path / "embeddings.parquet"))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM read_parquet('{tmp_path}/embeddings.parquet/*.parquet')")
    found = con.execute(cover_tree.SQL)
    names = [x[0] for x in found.description]
    got = cover_tree.op4_cover_tree(spark, str(tmp_path)).select(*names).collect()
    assert sorted(map(tuple, got)) == sorted(found.fetchall())


def test_dual_search_prunes():
    rng = np.random.default_rng(2)
    far = np.concatenate([rng.integers(-5, 5, (500, 8)) + c for c in (np.full(8, 300), np.full(8, -300), np.zeros(8))]).astype(np.int64)
    tree, q = cover_tree.CoverTree(np.arange(1500), far), cover_tree.CoverTree(np.arange(2000, 2010), far[:10])
    best, calls = cover_tree.Best(10, 5, np.full(10, cover_tree._NONE)), []
    was, cover_tree.products = cover_tree.products, lambda a, b: calls.append(len(b)) or was(a, b)
    try:
        cover_tree.dual_search(q, tree, best)
    finally:
        cover_tree.products = was
    assert sum(calls) < 1500
    assert (best.scores == -np.sort(-(q.points @ far.T.astype(float)), axis=1)[:, :5]).all()


def plain_licenses(text, templates):
    """Names of the templates of which some stretch of the text contains enough, by sets of word tuples: every stretch as long as an occurrence may be."""
    edges = "\"'`.,:;!?()[]{}<>*#-_/\\|"
    words = lambda t: [w for w in (x.strip(edges) for x in re.sub("[A-Z]", lambda m: m[0].lower(), t or "").encode().decode("latin-1").split(" ")) if w]
    flat = lambda t: words(re.sub(r"[\x09-\x0d]", " ", t or ""))
    own, found = flat(text), set()
    for name, t in templates.items():
        w = flat(t)
        k = min(5, len(w))
        want = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)}
        runs = [tuple(own[i : i + k]) for i in range(len(own) - k + 1)]
        wide = int(1.25 * len(want) + 0.999)
        if any(len(want & set(runs[i : i + wide])) / len(want) >= 0.75 for i in range(max(1, len(runs) - wide + 1))):
            found.add(name)
    return found


def test_license_scan(spark, docs, none):
    rng = random.Random(31)
    t = license_scan.TEMPLATES
    mit = t["mit"].split()
    rows = [(1, "Before. " + t["mit-notice"] + " after it all"), (2, "x " * 300 + " ".join(mit[:20] + ["CHANGED"] + mit[21:]) + " y" * 100), (3, "Released under another license entirely."), (4, None), (5, ""), (6, t["bsd-2-clause"].upper()), (6, t["bsd-2-clause"])]
    got = license_scan.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert collections.Counter((x.doc_id, x.license) for x in got) == {(1, "mit-notice"): 1, (2, "mit"): 1, (6, "bsd-2-clause"): 2}
    library, h = license_scan.Library(t), license_scan._Hashes()
    # all kinds of texts, the very long one too: bands against every window, and both against an independent scan
    texts = [x.text for x in docs.collect()] + [x[1] for x in rows]
    filler = lambda n: " ".join("".join(rng.choice("abcdef") for _ in range(5)) for _ in range(n))
    for name, body in t.items():
        w = body.split()
        for _ in range(rng.randrange(len(w) // 60 + 1)):
            w[rng.randrange(len(w))] = "edited"
        texts.append(f"{filler(rng.randrange(200))} {' '.join(w)} {filler(rng.randrange(90))}")
        texts.append(f"{filler(30)} {' '.join(w[: len(w) // 3])}")
    found = license_scan.scan_texts(texts, library, h)
    assert found == license_scan.scan_texts(texts, library, h, use_bands=False)
    names = collections.defaultdict(set)
    for i, name, _, _ in found:
        names[i].add(name)
    for i, x in enumerate(texts):
        assert plain_licenses(x, t) <= names[i]
        if len(x or "") < 9000:  # a window may be a block longer than the stretch
            assert len(names[i] - plain_licenses(x, t)) <= 1
    assert sum(map(len, names.values())) > len(t)
    assert license_scan.scan(none).count() == 0
    assert license_scan.scan(docs, {}).count() == 0


def leaf_sets(spark, texts):
    """Leaves by the module's cuts; what's made of them is then recomputed in Python."""
    from pyspark.sql import functions as F

    texts = sorted(set(texts))
    got = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "i long, t string").select("i", merkle.leaves(F.col("t")).alias("x")).collect()
    return {texts[r.i]: list(r.x) for r in got}


def jaccard(a, b):
    """Of the SKETCH smallest of both together, those in both: exact where there are fewer."""
    cut = lambda x: set(sorted(x)[: merkle.SKETCH])
    u = cut(cut(set(a)) | cut(set(b)))
    return len(u & cut(set(a)) & cut(set(b))) / len(u)


def test_merkle(spark, docs, none):
    """Every row, the last known document and null ids included, against plain Python."""
    from pyspark.sql import functions as F

    hashes = {(x.doc_id, x.text or ""): x.h for x in docs.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("h")).collect()}
    rows = [(x.doc_id, x.text or "") for x in docs.collect()]
    order = sorted(set(rows), key=lambda x: (x[0] is None, -(x[0] or 0), -hashes[x]))
    after = dict(zip(order, order[1:] + order[:1]))
    edit = {x: x[1][: len(x[1]) - len(x[1]) // 3] + after[x][1][: len(x[1]) // 3] for x in order}
    leaf = leaf_sets(spark, [t for _, t in rows] + list(edit.values()))
    want = collections.Counter((x[0], len(x[1]), edit[x], round(jaccard(leaf[x[1]], leaf[edit[x]]), 9), round(jaccard(leaf[x[1]], leaf[after[x][1]]), 9)) for x in rows)
    got = merkle.edits(docs).collect()
    assert collections.Counter((x.doc_id, x.n_chars, x.edited, round(x.near_edited, 9), round(x.near_next, 9)) for x in got) == want
    assert len(got) == len(rows) > len(set(rows))
    prints = collections.defaultdict(set)
    for x in merkle.fingerprints(docs).collect():
        prints[x.doc_id].add(x.fingerprint)
    assert all(x.fingerprint in prints[x.doc_id] for x in got)
    by_text = collections.defaultdict(set)
    for x in got:
        by_text[x.edited].add(x.edited_fingerprint)
    assert all(len(v) == 1 for v in by_text.values()) and len({v.copy().pop() for v in by_text.values()}) == len(by_text)
    assert max(len(x.fingerprint) for x in got) <= 64 + 2 + 17 * (merkle.SKETCH + merkle.MOST_NODES)
    assert merkle.edits(none).count() == 0


def test_merkle_lone_document(spark):
    df = spark.createDataFrame([(3, "one two three four five six")], "doc_id long, text string")
    (x,) = merkle.edits(df).collect()
    assert x.edited == "one two three four" + "one two t" and x.near_next == 1.0


def test_merkle_locates_edits(spark):
    from pyspark.sql import functions as F

    text = "\n".join(f"line {i} of the long text about that subject" for i in range(400))
    df = spark.createDataFrame([(text, text.replace("line 200 ", "line two hundred "))], "a string, b string")
    f = df.select(*(merkle.fingerprint(merkle.leaves(F.col(c))).alias(c) for c in "ab"))
    x = f.select(merkle.locate(F.col("a"), F.col("b")).alias("found"), F.size(merkle.locate(F.col("a"), F.col("a"))).alias("none"), F.size(F.split(F.element_at(F.split("a", ":"), 2), "[.]")).alias("all"), merkle.likeness(merkle.sketch_of(F.col("a")), merkle.sketch_of(F.col("b"))).alias("near")).first()
    assert 1 <= len(x.found) <= 2 and x.none == 0 and x.all > 20 and x.near > 0.9
    parts = merkle.sections(spark.createDataFrame([(1, text)], "doc_id long, text string")).orderBy("section").collect()
    assert [p.start for p in parts] == list(np.cumsum([0] + [p.n_chars for p in parts])[:-1]) and sum(p.n_chars for p in parts) == len(text)
    # the nodes named are where the edit is
    place = text.index("line 200 ")
    assert any(p.node in x.found and p.start <= place < p.start + p.n_chars for p in parts)


def test_merkle_levels_are_bounded(spark, monkeypatch):
    from pyspark.sql import functions as F

    monkeypatch.setattr(merkle, "MOST_NODES", 8)
    text = "\n".join(f"row {i}" for i in range(4000))
    df = spark.createDataFrame([(text, text.replace("row 77\n", "row x\n"), text + "!")], "a string, b string, c string")
    f = df.select(*(merkle.fingerprint(merkle.leaves(F.col(c))).alias(c) for c in "abc")).first()
    tops = [x.split(":")[1].split(".") for x in f]
    assert all(len(x) <= 40 for x in tops) and len({x.split(":")[0] for x in f}) == 3
    assert len(set(tops[0]) - set(tops[1])) <= 2


def test_chat_format(spark):
    import duckdb

    rows = [(1, 0, "user", "hi"), (1, 1, "bot", "ho"), (2, 0, "user", "hi"), (3, 0, "user", "hi"), (3, 1, "bot", "ho"), (3, 2, "user", None), (4, 0, "user", "hi"), (4, 1, "bot", ""), (5, 0, None, "x"), (6, 0, "bot", "hi"), (6, 0, "bot", "hi"), (7, None, "user", "hi"), (7, 3, "bot", "ho"), (8, 5, "user", "hi"), (9, 0, "user", "same"), (10, 0, "user", "same")]
    rows += [(11, i, "user", f"t{i}") for i in range(2500)] + [(12, i, "user", f"t{i}") for i in range(1200)]
    df = spark.createDataFrame([x + (7, "h") for x in rows], "conv_id long, turn long, role string, text string, place long, h1 string").repartition(5)
    got = chat_format.format_chats(df)
    con = duckdb.connect()
    con.register("conversations", __import__("pandas").DataFrame(rows, columns=["conv_id", "turn", "role", "text"]).astype({"turn": "Int64"}))
    assert sorted(map(tuple, got.collect())) == sorted(con.execute(chat_format.SQL).fetchall())
    ids = {x.conv_id for x in got.collect()}
    assert 2 not in ids and 12 not in ids and 10 not in ids and {3, 4, 9, 11} <= ids
    assert chat_format.format_chats(df.limit(0)).count() == 0


def test_language_id(spark, docs, none):
    rng = random.Random(4)
    bags = {"en": "the of and is that this with for are on".split(), "de": "der die und nicht schön über auf mit für ist".split(), "fr": "le la été où être dans avec pour très déjà".split()}
    rows = [(i, " ".join(rng.choice(bags[g]) for _ in range(rng.randrange(3, 80))), g) for i, g in enumerate(rng.choice(list(bags)) for _ in range(600))]
    train = spark.createDataFrame(rows[:400], "doc_id long, text string, lang string")
    model = language_id.learn(train)
    assert model.langs == ["de", "en", "fr"]
    test = spark.createDataFrame([*rows[400:], (900, None, "en"), (901, "", None), (902, "123 !?", "de"), (902, "123 !?", "de"), (903, "der " * 100_000, "de")], "doc_id long, text string, lang string")
    got = language_id.predict(test, model).collect()
    assert len(got) == 205
    by = {x.doc_id: x for x in got}
    assert sum(by[i].lang_pred == g for i, _, g in rows[400:]) >= 196
    assert all(by[i].lang_pred == "und" and by[i].score == 1 for i in (900, 901, 902)) and by[903].lang_pred == "de"
    assert all(0 <= x.score <= 1 for x in got)
    assert language_id.learn(none) is None
    assert {x.lang_pred for x in language_id.predict(docs, None).collect()} == {"und"}
    assert language_id.predict(none, model).count() == 0
    assert (np.abs(model.weights) < 1e-12).mean() > 0.5  # sparse


def plain_grams(text):
    """Buckets of a text's n-grams, a space before it and after."""
    padded, out = " " + text + "   ", []
    for start in range(len(text) + 1):
        h = 0
        for k in range(3):
            h = (h * 0x01000193 & 0xFFFFFFFF) ^ ord(padded[start + k])
            out.append(((h ^ h >> 15) * (0x2C1B3C6D + 2 * k) & 0xFFFFFFFF) >> 16)
    return out


def plain_ftrl(rows, langs, idf, names):
    """Follow the regularised leader with an elastic net, coordinate by coordinate."""
    z, n, w = (collections.defaultdict(float) for _ in range(3))
    order = np.random.default_rng(11)
    L = language_id
    for _ in range(L.EPOCHS):
        at = order.permutation(len(rows))
        for run in np.array_split(at, max(1, len(at) // L.BATCH)):
            g = collections.defaultdict(float)
            for i in run:
                counts = collections.Counter(plain_grams(rows[i]))
                x = {f: c / sum(counts.values()) * idf[f] * L._SCALE for f, c in counts.items()} | {"bias": 1.0}
                logit = [sum(w[f, c] * v for f, v in x.items()) for c in range(len(names))]
                p = [math.exp(v - max(logit)) for v in logit]
                p = [v / sum(p) for v in p]
                p[names.index(langs[i])] -= 1
                for f, v in x.items():
                    for c in range(len(names)):
                        g[f, c] += v * p[c] / len(run)
            for key, v in g.items():
                step = (math.sqrt(n[key] + v * v) - math.sqrt(n[key])) / L.ALPHA
                z[key] += v - step * w[key]
                n[key] += v * v
                shrunk = math.copysign(max(abs(z[key]) - L.L1, 0.0), z[key])
                w[key] = -shrunk / ((L.BETA + math.sqrt(n[key])) / L.ALPHA + L.L2)
    return w


def test_language_id_fit_logits_and_temperature():
    rng = random.Random(14)
    bags = {"de": "der die und nicht schön".split(), "en": "the of and is that".split()}
    langs = [rng.choice(list(bags)) for _ in range(60)]
    texts = [" ".join(rng.choice(bags[g]) for _ in range(rng.randrange(1, 6))) for g in langs]
    idf = np.random.default_rng(15).uniform(1, 3, language_id.FEATURES)
    model = language_id.fit([language_id.pack_counts(x) for x in texts[:40]], langs[:40], idf, ["de", "en"])
    w = plain_ftrl(texts[:40], langs[:40], idf, ["de", "en"])
    for (f, c), v in w.items():
        got = model.bias[c] if f == "bias" else model.weights[f, c] / (idf[f] * language_id._SCALE)
        assert got == pytest.approx(v, abs=2e-4)
    logits = lambda t: [sum(float(model.weights[f, c]) for f in plain_grams(t)) / len(plain_grams(t)) + model.bias[c] for c in (0, 1)]
    some = [*texts[40:], "日本", "x" * 3000]
    assert np.allclose(model.logits(some), [logits(t) for t in some], atol=1e-3)
    language_id.calibrate(model, [language_id.pack_counts(x) for x in texts[40:]], langs[40:])

    def loss(t):
        out = 0.0
        for x, g in zip(texts[40:], langs[40:]):
            v = [y / t for y in logits(x)]
            out += math.log(sum(math.exp(y - max(v)) for y in v)) + max(v) - v[["de", "en"].index(g)]
        return out

    grid = np.geomspace(0.02, 20, 121).tolist()
    assert loss(model.temperature) <= min(map(loss, grid)) + 1e-3
    found, p, known = model.predict(some)
    has = {f for f, _ in w if f != "bias" and np.any(model.weights[f])}
    assert np.allclose(known, [np.mean([f in has for f in plain_grams(x)]) for x in some]) and known[-2] < 0.5
    for x, g, s in zip(some, found, p):
        v = [y / model.temperature for y in logits(x)]
        assert g == ["de", "en"][int(v[1] > v[0])] and s == pytest.approx(1 / (1 + math.exp(-abs(v[0] - v[1]))), abs=1e-3)


def test_language_id_samples_different_texts(spark):
    """Copies of a text are one row of the sample: a bound of few rows still holds other texts."""
    copies = [(i, "the same words again", "en") for i in range(500)]
    rows = copies + [(1000 + i, f"word{i} other of and", "en") for i in range(20)] + [(2000 + i, f"wort{i} und nicht", "de") for i in range(20)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.learn(df, fit_rows=30, calibrate_rows=6)
    got = {x.doc_id: x.lang_pred for x in language_id.predict(df, model).collect()}
    assert all(got[i] == "en" for i in range(1000, 1020)) and all(got[i] == "de" for i in range(2000, 2020))
    clash = df.withColumn("_read", df["doc_id"]).withColumn("lang_pred", df["lang"])
    assert language_id.predict(clash, model).count() == len(rows)


def brute_components(rows):
    def sets(t):
        w = (t or "").encode().lower().split()
        return set() if not w else {tuple(w)} if len(w) < 5 else {tuple(w[i : i + 5]) for i in range(len(w) - 4)}

    s = [sets(t) for _, t in rows]
    up = list(range(len(rows)))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if s[a] and s[b] and 4 * len(s[a] & s[b]) >= 3 * len(s[a] | s[b]):
                up[find(a)] = find(b)
    least = {}
    for a in range(len(rows)):
        if rows[a][0] is not None:
            least[find(a)] = min(least.get(find(a), 1 << 60), rows[a][0])
    return collections.Counter((i, len(x), least.get(find(a)), i == least.get(find(a))) for a, ((i, _), x) in enumerate(zip(rows, s)))


def test_lsh_forest(docs, none):
    rows = [(x.doc_id, x.text) for x in docs.collect()]
    got = collections.Counter((x.doc_id, x.n_shingles, x.component_id, x.kept) for x in lsh_forest.near_duplicates(docs).collect())
    assert got == brute_components(rows)
    assert lsh_forest.near_duplicates(none).count() == 0


def test_lsh_forest_dense_family(spark, monkeypatch):
    """One family whose pairs lie about the threshold, a passage that unlike texts share, and groups of exact copies."""
    rng = random.Random(9)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    base, passage = [word() for _ in range(70)], [word() for _ in range(60)]
    texts = []
    for _ in range(160):
        t = list(base)
        for _ in range(rng.randrange(0, 4)):
            t[rng.randrange(len(t))] = word()
        texts.append(" ".join(t))
    texts += [" ".join([word() for _ in range(rng.randrange(5, 200))] + passage) for _ in range(120)]
    texts += [texts[-1]] * 20 + [texts[3]] * 20
    rows = list(enumerate(texts))
    seen = []
    was = lsh_forest._rest
    monkeypatch.setattr(lsh_forest, "_rest", lambda *a: seen.append(1) or was(*a))
    monkeypatch.setattr(lsh_forest._with_counts, "__defaults__", (20, 100_000))
    monkeypatch.setattr(lsh_forest, "BLOCK", 16)
    monkeypatch.setattr(lsh_forest, "ASKING", 8)
    got = lsh_forest.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert seen  # the exact way for large regions ran
    assert collections.Counter((x.doc_id, x.n_shingles, x.component_id, x.kept) for x in got) == brute_components(rows)


@pytest.mark.parametrize("name", ["op4_cover_tree", "op7_chat_format", "op9_lsh_forest"])
def test_query_equals_sql(spark, name):
    from harness import compare

    from blockbwt.llm import queries

    assert compare(spark, queries.queries()[name], queries.oracle_sql()[name], "/root/testdata/sf0.001") == ""


def test_components(spark):
    links = [(b"a", b"b"), (b"b", b"c"), (b"x", b"y"), (b"z", b"y"), (b"m", b"m")] + [(f"p{i:03d}".encode(), f"p{i + 1:03d}".encode()) for i in range(40)]
    got = {bytes(x.node): bytes(x.root) for x in lsh_forest.components(spark.createDataFrame(links, "a binary, b binary")).collect()}
    assert got == {b"b": b"a", b"c": b"a", b"y": b"x", b"z": b"x"} | {f"p{i:03d}".encode(): b"p000" for i in range(1, 41)}


def test_mixing(spark, docs, none):
    got = mixing.mix(docs).collect()
    rows = docs.collect()
    size = lambda t: len(WORD.findall(t or ""))
    assert collections.Counter((x.doc_id, x.source, x.size) for x in got) == collections.Counter((x.doc_id, x.source, size(x.text)) for x in rows)
    total = collections.Counter()
    for x in rows:
        total[x.source] += size(x.text)
    order = sorted((s for s in total if s is not None)) + ([None] if None in total else [])
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    target, open_ = dict.fromkeys(order, 0.0), set(order)
    left = 1.5 * sum(total.values())
    while open_:
        level = left / sum(weight[s] for s in open_)
        full = {s for s in open_ if weight[s] * level > 2 * total[s]}
        if not full:
            target.update({s: weight[s] * level for s in open_})
            break
        for s in full:
            target[s] = 2.0 * total[s]
            left -= target[s]
        open_ -= full
    taken = collections.Counter()
    for x in got:
        assert x.source_size == total[x.source] and x.target == pytest.approx(target[x.source]) and 0 <= x.taken <= 2 * x.size
        taken[x.source] += x.taken
    assert all(abs(taken[s] - target[s]) <= 1 for s in order)
    assert sorted(map(str, got)) == sorted(map(str, mixing.mix(docs).collect()))
    assert mixing.mix(none).count() == 0


def test_mixing_chooses_by_key(spark, docs, monkeypatch):
    """What is taken of every row, from its key alone: whole epochs, then the smallest keys up to the rest."""
    from pyspark.sql import functions as F

    quality = docs.where("doc_id is not null").select("doc_id", F.when(F.col("doc_id") % 2 == 0, 2.0).otherwise(0.5).alias("quality_weight")).distinct()
    weight = dict(map(tuple, quality.collect()))
    size = mixing.words_in(F.col("text"))
    w = F.when(F.col("doc_id").isNull(), 1.0).when(F.col("doc_id") % 2 == 0, 2.0).otherwise(0.5)
    keyed = docs.select("doc_id", "source", size.alias("size"), mixing.sampling_key(F.col("doc_id"), size, F.xxhash64("text"), w).alias("key")).collect()
    assert set(weight.values()) == {2.0, 0.5} and len({x.key for x in keyed}) >= len(keyed) - 4  # only equal rows share one
    runs = []
    for limit in (mixing.ONE_TASK_SOURCES, 0):
        monkeypatch.setattr(mixing, "ONE_TASK_SOURCES", limit)
        runs.append(sorted(map(str, mixing.mix(docs, quality=quality).collect())))
    assert runs[0] == runs[1]
    got = mixing.mix(docs, quality=quality).collect()
    target = {x.source: (x.target, x.source_size) for x in got}
    want = collections.Counter()
    for source, (t, total) in target.items():
        epochs = int(t // total) if total else 0
        left = round(t - epochs * total)
        for x in sorted((x for x in keyed if x.source == source), key=lambda x: x.key):
            part = min(x.size, max(0, left))
            left -= part
            want[(x.doc_id, source, x.size, epochs * x.size + part)] += 1
    assert collections.Counter((x.doc_id, x.source, x.size, x.taken) for x in got) == want


def test_mixing_prefers_quality_and_applies(spark):
    rows = [(i, "w " * 10, "s", i % 2) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, q int")
    from pyspark.sql import functions as F

    quality = df.select("doc_id", mixing.quality_weight(F.col("q")).alias("quality_weight"))
    mixed = common.materialise(mixing.mix(df, quality=quality, share=0.505), "mix")
    good = sum(x.taken for x in mixed.collect() if x.doc_id % 2)
    bad = sum(x.taken for x in mixed.collect() if not x.doc_id % 2)
    assert good + bad == 2020 and good > 2 * bad
    out = mixing.apply(df, mixed).collect()
    assert sum(len(WORD.findall(x.text)) for x in out) == 2020
