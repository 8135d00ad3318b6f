"""Operator 8: language ID by sparse multinomial logistic regression.

Features are character n-grams of the lower-cased text, hashed to FEATURES
buckets; their value is the share of the text's n-grams times the inverse
document frequency over all training documents. The model is fitted with
follow-the-regularised-leader steps under an elastic net (the L1 part keeps most
weights at zero) on a bounded sample of FIT_ROWS training documents and a
temperature is fitted on further CALIBRATE_ROWS of them; both bounds are
parameters, and both samples are those of the smallest hashes, spread evenly
over the languages. A sampled text is read whole: its n-grams are counted where
it is, and the driver gets counts of at most FEATURES buckets, packed. Document
frequencies cover every training document.

Text of no learned language is told by `known`, the share of its n-grams whose
bucket has a weight: a probability among the learned languages can't tell it.

A prediction reads every character of the text. Since a feature's value is
linear in its count, a text's logits are a mean of per-n-gram weights: one
gather and one segmented sum over a batch, whatever the texts' lengths.

Defined results: a null text or one without a letter is `und` with score 1 and
known 0; a
null lang isn't learned from; without any labelled training document all other
texts are `und` with score 0; with one language it's that one with score 1; rows
that repeat are each predicted; an empty table gives no row.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

FEATURES, ORDERS = 1 << 16, (1, 2, 3)
FIT_ROWS, CALIBRATE_ROWS = 6_000, 2_000
ALPHA, BETA, L1, L2, EPOCHS, BATCH = 0.5, 1.0, 1e-4, 1e-5, 4, 32
_SCALE = 30.0  # shares are small: a constant gain, undone by nothing and tuned by the temperature
_BLOCK = 1 << 18


def ngrams(texts: list[str]) -> tuple[list[np.ndarray], np.ndarray]:
    """For each order the buckets at every place of the joined texts, and where each text begins; a space stands before and after each text."""
    apart = " " * max(ORDERS)  # so many that no n-gram reaches into the next text
    joined = " " + apart.join(texts) + apart
    points = np.frombuffer(joined.encode("utf-32-le"), np.uint32)
    lens = np.array([len(x) + 1 for x in texts], np.int64)
    starts = np.concatenate([[0], np.cumsum(lens)])
    own = np.arange(starts[-1]) + np.repeat(np.arange(len(texts)) * (len(apart) - 1), lens)
    out, h = [], np.zeros(len(points), np.uint32)
    for k in range(max(ORDERS)):
        h = h[: len(points) - k] * np.uint32(0x01000193) ^ points[k:]
        if k + 1 in ORDERS:
            mixed = (h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D + 2 * k)
            out.append((mixed >> np.uint32(16)).astype(np.uint16)[own])
    return out, starts


def _lower(texts: list[str | None]) -> list[str]:
    return [(x or "").lower() for x in texts]


def _blocks(texts: list[str]):
    """(from, to) of runs of texts of about _BLOCK characters."""
    a = size = 0
    for i, x in enumerate(texts):
        size += len(x)
        if size >= _BLOCK:
            yield a, i + 1
            a, size = i + 1, 0
    if a < len(texts):
        yield a, len(texts)


def _frequencies(batches):
    """Document frequency of each bucket within the partition."""
    df, n = np.zeros(FEATURES, np.int64), 0
    for batch in (x for whole in batches for x in common.slices(whole, 0)):
        texts = _lower(batch.column(0).to_pylist())
        n += len(texts)
        for a, b in _blocks(texts):
            grams, starts = ngrams(texts[a:b])
            for i in range(b - a):
                seen = np.zeros(FEATURES, bool)
                for g in grams:
                    seen[g[starts[i] : starts[i + 1]]] = True
                df += seen
    yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([df.astype("<i8").tobytes()], pa.binary())], names=["n", "df"])


def document_frequencies(texts: DataFrame) -> tuple[int, np.ndarray]:
    """Over all rows: (documents, frequency of each bucket). Tables of a fixed size are summed in a tree, so the driver gets a few of them."""

    def add(batches):
        n, df = 0, np.zeros(FEATURES, np.int64)
        for batch in batches:
            n += sum(batch.column(0).to_pylist())
            for x in batch.column(1).to_pylist():
                df += np.frombuffer(x, "<i8")
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([df.astype("<i8").tobytes()], pa.binary())], names=["n", "df"])

    partial = texts.mapInArrow(common.trimmed(_frequencies), "n long, df binary")
    found = partial.repartition(8).mapInArrow(add, "n long, df binary").collect()
    return sum(x.n for x in found), np.sum([np.frombuffer(x.df, "<i8") for x in found], axis=0)


class Model:
    def __init__(self, langs: list[str], weights: np.ndarray, bias: np.ndarray, temperature: float = 1.0):
        self.langs, self.weights, self.bias, self.temperature = langs, weights, bias, temperature

    def logits(self, texts: list[str]) -> np.ndarray:
        """weights has the idf and the gain in it already."""
        return self._read(texts)[0]

    def _read(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Logits, and the share of each text's n-grams that have a weight."""
        out, known = np.empty((len(texts), len(self.langs))), np.empty(len(texts))
        has = (self.weights != 0).any(1).astype(np.float32)
        for a, b in _blocks(texts):
            grams, starts = ngrams(texts[a:b])
            sums = np.zeros((b - a, len(self.langs)))
            for g in grams:
                for c in range(len(self.langs)):
                    sums[:, c] += np.add.reduceat(self.weights[:, c][g], starts[:-1])
            n = np.diff(starts) * len(grams)
            out[a:b] = sums / n[:, None] + self.bias
            known[a:b] = sum(np.add.reduceat(has[g], starts[:-1], dtype=np.float64) for g in grams) / n
        return out, known

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Languages, their probabilities, and the share of known n-grams."""
        z, known = self._read(texts)
        z = z / self.temperature
        p = np.exp(z - z.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        best = p.argmax(1)
        return [self.langs[i] for i in best], p[np.arange(len(best)), best], known


def pack_counts(text: str) -> bytes:
    """The buckets of a whole text's n-grams and how often each occurs."""
    grams, _ = ngrams([text])
    n = np.zeros(FEATURES, np.int64)
    for g in grams:
        n += np.bincount(g, minlength=FEATURES)
    f = np.flatnonzero(n)
    return common.pack(np.stack([f, n[f]]).astype("<u4"))


def _shares(packed: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Buckets and their shares of the text's n-grams."""
    f, n = common.unpack_array(packed, "<u4").reshape(2, -1)
    return f, n / n.sum(dtype=np.int64)


def _counted(batches):
    """(text, lang, h) -> (lang, h, grams)."""
    for batch in (x for whole in batches for x in common.slices(whole, 0)):
        grams = [pack_counts(x) for x in _lower(batch.column(0).to_pylist())]
        yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(grams, pa.binary())], names=["lang", "h", "grams"])


def fit(packed: list[bytes], langs: list[str], idf: np.ndarray, names: list[str]) -> Model:
    """FTRL-proximal with per-coordinate rates, L1 and L2; steps of BATCH documents, whose counts alone are unpacked."""
    k = len(names)
    y = np.array([names.index(x) for x in langs])
    z, n, w = np.zeros((FEATURES + 1, k)), np.zeros((FEATURES + 1, k)), np.zeros((FEATURES + 1, k))
    order = np.random.default_rng(11)
    for _ in range(EPOCHS):
        at = order.permutation(len(packed))
        for run in np.array_split(at, max(1, len(at) // BATCH)):
            rows = [_shares(packed[i]) for i in run]
            f = np.concatenate([np.append(a, FEATURES) for a, _ in rows]).astype(np.int64)
            x = np.concatenate([np.append(b * idf[a] * _SCALE, 1.0) for a, b in rows])
            ends = np.cumsum([0, *(len(a) + 1 for a, _ in rows)])
            logits = np.add.reduceat(w[f] * x[:, None], ends[:-1])
            p = np.exp(logits - logits.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(run)), y[run]] -= 1
            used, back = np.unique(f, return_inverse=True)
            g = np.zeros((len(used), k))
            np.add.at(g, back, x[:, None] * np.repeat(p, np.diff(ends), axis=0))
            g /= len(run)
            step = (np.sqrt(n[used] + g * g) - np.sqrt(n[used])) / ALPHA
            z[used] += g - step * w[used]
            n[used] += g * g
            shrunk = np.sign(z[used]) * np.maximum(np.abs(z[used]) - L1, 0)
            w[used] = -shrunk / ((BETA + np.sqrt(n[used])) / ALPHA + L2)
    return Model(names, np.ascontiguousarray((w[:-1] * idf[:, None] * _SCALE).astype(np.float32)), w[-1])


def calibrate(model: Model, packed: list[bytes], langs: list[str]) -> None:
    """The temperature of least log loss, on rows that weren't fitted, over a grid of rising ones."""
    if not packed or len(model.langs) < 2:
        return
    z = np.array([b @ model.weights[a] + model.bias for a, b in map(_shares, packed)])
    y = np.array([model.langs.index(x) for x in langs])

    def loss(t: float) -> float:
        s = z / t
        s = s - s.max(1, keepdims=True)
        return float((np.log(np.exp(s).sum(1)) - s[np.arange(len(y)), y]).mean())

    model.temperature = min(np.geomspace(0.02, 20, 121).tolist(), key=loss)


def learn(df: DataFrame, text: str = "text", lang: str = "lang", order: Column | None = None, fit_rows: int = FIT_ROWS, calibrate_rows: int = CALIBRATE_ROWS) -> Model | None:
    """A model of all of df's rows that have text and lang; None if there are none.

    The samples take from every language its different texts of the smallest
    hashes, up to an equal share of the bound, and of each its whole text.
    """
    common.small_batches(df.sparkSession)
    rows = df.select(F.col(text).alias("text"), F.col(lang).alias("lang"))
    rows = rows.where("text is not null and lang is not null")
    h = F.pmod(F.xxhash64("text"), F.lit(1 << 40))
    hashed = rows.withColumn("h", h)
    # different texts of each language, a row for each
    counts = {x.lang: x.n for x in hashed.groupBy("lang").agg(F.approx_count_distinct("h", 0.02).alias("n")).collect()}
    if not counts:
        return None
    names = sorted(counts)
    n, df_table = document_frequencies(rows.select("text"))
    idf = np.log((1 + n) / (1 + df_table)) + 1
    each = -(-(fit_rows + calibrate_rows) // len(names))
    # below these hashes each language has about twice what is needed; the exact smallest follow
    bounds = {x: min(1.0, 2.0 * each / max(1, counts[x])) for x in names}
    below = F.element_at(F.create_map(*[F.lit(v) for x, b in bounds.items() for v in (x, b)]), F.col("lang")) * float(1 << 40)
    # copies are one: keys alone find the first row of each text
    once = hashed.where(F.col("h") <= below).withColumn("row", F.monotonically_increasing_id())
    first = once.groupBy("lang", "h").agg(F.min("row").alias("row"))
    ranked = once.join(first, ["lang", "h", "row"], "left_semi").select("text", "lang", "h").mapInArrow(common.trimmed(_counted), "lang string, h long, grams binary")
    ranked = ranked.withColumn("k", F.row_number().over(Window.partitionBy("lang").orderBy("h", "grams"))).where(F.col("k") <= each)
    sample = ranked.orderBy("h", "grams").collect()
    every = max(2, (fit_rows + calibrate_rows) // max(1, calibrate_rows))
    keep, held = [x for i, x in enumerate(sample) if i % every], sample[::every]
    model = fit([x.grams for x in keep], [x.lang for x in keep], idf, names)
    calibrate(model, [x.grams for x in held], [x.lang for x in held])
    return model


def predict(df: DataFrame, model: Model | None, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """The columns `keep` with lang_pred, score and known, a row for each row of df."""
    common.small_batches(df.sparkSession)
    sent = df.sparkSession.sparkContext.broadcast(model)  # FEATURES times the languages, whatever the input

    def run(batches):
        import regex

        letter, model = regex.compile(r"\p{L}").search, sent.value
        for batch in (x for whole in batches for x in common.slices(whole, 0)):
            texts = batch.column(0).to_pylist()
            has = [i for i, x in enumerate(texts) if x and letter(x)]
            langs, score, known = ["und"] * len(texts), np.ones(len(texts)), np.zeros(len(texts))
            if model is None:
                score[has] = 0.0
            elif has:
                found, score[has], known[has] = model.predict(_lower([texts[i] for i in has]))
                for i, x in zip(has, found):
                    langs[i] = x
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(langs), pa.array(score), pa.array(known)], names=[*names, "lang_pred", "score", "known"])

    kept = df.select(F.col(text).alias("_read"), *keep)
    names = kept.columns[1:]
    types = dict(kept.dtypes)
    schema = ", ".join(f"`{c}` {types[c]}" for c in names)
    return kept.mapInArrow(common.trimmed(run), f"{schema}, lang_pred string, score double, known double")


def remainder(doc_id: Column, k: int) -> Column:
    """crc32 of the id as text; a null id counts as 0."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(k))


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text", "lang", (remainder(F.col("doc_id"), 3) == 1).alias("held_out"))
    model = learn(docs.where("not held_out"))
    return predict(docs, model, keep=("doc_id", "held_out"))
