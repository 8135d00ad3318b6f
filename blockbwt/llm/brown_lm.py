"""Operator 3: a Brown class-based bigram model and its scores.

P(text) is the product over its tokens (words, then one end) of
P(class | class before) * P(word | class); the end is a class of its own and
also stands before the first word.

Classes come from exchange clustering. The criterion is the likelihood of the
class bigrams on both sides of a word: the sum over classes c and contexts v of
n(v, c) log n(v, c), less n(c) log n(c) for each side, where a context is the
class of the word before or of the word after.

1. The CLASSES most frequent words found the classes, and every word of the
   vocabulary goes to the class that gains most by it. Nothing has a class yet,
   so contexts are here PROVISIONAL classes of the word before, given by a hash.
2. In each of PASSES passes contexts are the classes of the pass before, counted
   anew over all training tokens; then every word of the vocabulary, however
   rare, is taken out of its class and put where the criterion gains most.

Gains are exact. The vocabulary is in parts; a part begins with the whole
corpus's counts by class and context, which are of a fixed size, and counts its
own moves as it goes on: its most frequent words one by one, rarer ones in
batches of a small share of its tokens. The moves of other parts are known from
the next pass on.

Smoothing: a word seen n times in its class has n / N(class) of the class; an
unseen word is one more outcome whose chance after a class is that of meeting a
word seen only once there, mixed with the corpus-wide one; class transitions are
mixed with the classes' own frequencies. The outcomes sum to one.

Documents are read once into chunks that hold every token's place in the chunk's
own dictionary. Dictionaries are dealt by word hash to parts, of which there are
MOST_PARTS at most, that sum counts and contexts and answer with places in the
vocabulary, and later with classes: a row a chunk and part, so a word as common
as one may wish is asked for once a chunk. A part holds its share of the
vocabulary; what chunks ask passes by it.

Defined results: null, empty and blank texts are the end token alone; null ids
hash as an empty string; an empty training set scores everything 0 tokens known,
base log10(1) a token and the model likewise; rows that repeat are each learned
and scored; an empty table gives no row.
"""

from __future__ import annotations

import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .byte_bpe import deal
from .common import pack, pack_words, unpack, unpack_array, unpack_words

CHUNK_CHARS, CLASSES, PROVISIONAL, PASSES, MOST_PARTS = 8 << 20, 48, 1024, 2, 1024
#: A batch of moves has at most this share of a part's tokens, and so many entries, or it is one word.
BATCH_SHARE, BATCH_ENTRIES = 0.002, 40_000
_MISSING = (1 << 32) - 1
#: No word contains white space, so this is none.
END = b" "
_CHUNK = "chunk long, docs array<long>, held binary, lens binary, places binary, parts array<int>, words array<binary>, counts array<binary>, rows array<binary>"


def _bucket(words: list[bytes]) -> np.ndarray:
    return np.fromiter((zlib.crc32(w) for w in words), np.uint32, len(words)).astype(np.int64) * 2654435761 % (1 << 32) >> 22


def _chunks(parts: int, most: int):
    """Chunks of documents; a document's tokens are its words and END."""

    def run(batches):
        task, seq = TaskContext.get().partitionId(), 0
        docs, held, lens, places, size = [], [], [], [], 0
        place: dict[bytes, int] = defaultdict()
        place.default_factory = place.__len__

        def chunk():
            nonlocal seq
            words = list(place)
            index, used, blobs = deal(words, parts)
            flat = index[np.concatenate(places)]
            length, learned = np.asarray(lens, np.int64), ~np.asarray(held, bool)
            train = np.repeat(learned, length)
            counts = np.bincount(flat[train], minlength=len(words)).astype(np.uint32)
            buckets = np.empty(len(words), np.int64)
            buckets[index] = _bucket(words)
            before = np.empty(len(flat), np.int64)
            before[1:] = buckets[flat[:-1]]
            begins = np.cumsum(length) - length
            before[begins] = _bucket([END])[0]
            key, n = np.unique(flat[train].astype(np.int64) * PROVISIONAL + before[train], return_counts=True)
            word = key // PROVISIONAL
            ends = np.cumsum([len(unpack_words(x)) for x in blobs])
            cuts = np.searchsorted(word, ends)
            rows, a, b = [], 0, 0
            for end, cut in zip(ends.tolist(), cuts.tolist()):
                row_len = np.bincount(word[b:cut] - a, minlength=end - a).astype(np.uint16)
                rows.append(pack_words([pack(row_len), pack((key[b:cut] % PROVISIONAL).astype(np.uint16)), pack(n[b:cut].astype(np.uint32))]))
                a, b = end, cut
            begins = [0, *ends.tolist()]
            row = {"chunk": task << 32 | seq, "docs": docs, "held": pack(np.asarray(held, np.uint8)), "lens": pack(length.astype(np.uint32)), "places": pack(flat), "parts": used, "words": blobs, "counts": [pack(counts[a:b]) for a, b in zip(begins, begins[1:])], "rows": rows}
            out = pa.RecordBatch.from_pylist([row], schema)
            seq += 1
            for x in (docs, held, lens, places, place):
                x.clear()
            return out

        for batch in batches:
            for doc, h, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                text = (text.as_py() or "").encode().lower()
                words = text.split()
                words.append(END)
                docs.append(doc)
                held.append(h)
                lens.append(len(words))
                places.append(np.fromiter(map(place.__getitem__, words), np.uint32, len(words)))
                size += len(text) + 16
                if size >= most:
                    yield chunk()
                    size = 0
        if docs:
            yield chunk()

    binaries = pa.list_(pa.binary())
    schema = pa.schema([("chunk", pa.int64()), ("docs", pa.list_(pa.int64())), ("held", pa.binary()), ("lens", pa.binary()), ("places", pa.binary()), ("parts", pa.list_(pa.int32())), ("words", binaries), ("counts", binaries), ("rows", binaries)])
    return run


def _summed(batches):
    """Rows come by part. Of each part: its training words, their counts, and their contexts as sparse rows."""
    part, place, counts, keys, sums, seen = None, None, [], [], [], set()

    def fold():
        key, at = np.unique(np.concatenate(keys), return_inverse=True)
        keys[:], sums[:] = [key], [np.bincount(at, np.concatenate(sums), len(key)).astype(np.int64)]

    def done():
        fold()
        n = np.zeros(len(place), np.int64)
        for index, c in counts:
            n[index] += c
        key = keys[0]
        order = np.flatnonzero(n)  # words of held-out documents alone aren't in the vocabulary
        new = np.cumsum(n > 0) - 1
        words = list(place)
        length = np.bincount(new[key // PROVISIONAL], minlength=len(order))
        return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([pack_words([words[i] for i in order.tolist()])], pa.binary()), pa.array([pack(n[order])], pa.binary()), pa.array([pack(length.astype(np.uint16))], pa.binary()), pa.array([pack((key % PROVISIONAL).astype(np.uint16))], pa.binary()), pa.array([pack(sums[0].astype(np.uint32 if not len(sums[0]) or sums[0].max() < 1 << 32 else np.uint64))], pa.binary()), pa.array([int(n.sum())], pa.int64()), pa.array([len(order)], pa.int64())], names=["part", "words", "counts", "lens", "contexts", "sums", "tokens", "types"])

    for batch in batches:
        for x in batch.to_pylist():
            if x["part"] != part:
                if part is not None and keys:
                    yield done()
                part, place, counts, keys, sums = x["part"], defaultdict(), [], [], []
                place.default_factory = place.__len__
            words = unpack_words(x["words"])
            index = np.fromiter(map(place.__getitem__, words), np.int64, len(words))
            counts.append((index, unpack_array(x["counts"], np.uint32)))
            length, context, n = unpack_words(x["rows"])
            keys.append(np.repeat(index, unpack_array(length, np.uint16)) * PROVISIONAL + unpack_array(context, np.uint16))
            sums.append(unpack_array(n, np.uint32).astype(np.float64))
            if len(keys) > 8:
                fold()
                sums[0] = sums[0].astype(np.float64)
    if part is not None and keys:
        yield done()


def _matrix(x: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row lengths, contexts, sums) of a vocabulary part."""
    context = unpack_array(x["contexts"], np.uint16)
    raw = unpack(x["sums"])
    return unpack_array(x["lens"], np.uint16), context, unpack_array(x["sums"], np.uint32 if len(raw) == 4 * len(context) else np.uint64)


def _f(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.maximum(x, 1e-12))


def criterion(table: np.ndarray, total: np.ndarray, sides: int) -> float:
    """What exchange raises; table: classes by contexts, total: tokens of each class."""
    return float(_f(table).sum() - sides * _f(total).sum())


def exchange(length: np.ndarray, context: np.ndarray, n: np.ndarray, own: np.ndarray, table: np.ndarray, total: np.ndarray, sides: int, share: float = BATCH_SHARE, entries: int = BATCH_ENTRIES) -> np.ndarray:
    """New classes of words, each where the criterion gains most by it.

    length, context, n: the words' sparse rows of counts by context, of `sides`
    sides. own: their classes, -1 for none yet (so not in the counts), -2 for a
    word that stays out. table and total: counts of everything, changed here by
    the moves made. Gains of a batch are against the counts before it.
    """
    own, k = own.copy(), len(total)
    ends = np.cumsum(length, dtype=np.int64)
    starts = ends - length
    weight = np.add.reduceat(np.append(n, 0).astype(np.float64), np.append(starts, len(n)))[:-1] if len(length) else np.zeros(0)
    weight[length == 0] = 0
    weight /= sides
    order = np.argsort(-weight, kind="stable")
    order = order[(own[order] != -2) & (length[order] > 0)]
    most = share * weight.sum()
    heavy, many = np.cumsum(weight[order]), np.cumsum(length[order], dtype=np.int64)
    a = 0
    while a < len(order):
        before, held = (heavy[a - 1], many[a - 1]) if a else (0.0, 0)
        b = max(a + 1, min(int(np.searchsorted(heavy, before + most, side="right")), int(np.searchsorted(many, held + entries, side="right"))))
        words = order[a:b]
        a = b
        size = length[words].astype(np.int64)
        begins = np.cumsum(size) - size
        at = np.arange(int(size.sum())) + np.repeat(starts[words] - begins, size)
        c, x = context[at].astype(np.int64), n[at].astype(np.float64)
        old, w = own[words], weight[words]
        has = old >= 0
        now, sums = table[:, c], np.broadcast_to(total[:, None], (k, len(words))).copy()
        each = np.repeat(old, size)
        inside = np.flatnonzero(each >= 0)
        now[each[inside], inside] -= x[inside]
        sums[old[has], np.flatnonzero(has)] -= w[has]
        gain = np.add.reduceat(_f(now + x) - _f(now), begins, axis=1) - sides * (_f(sums + w) - _f(sums))
        new = gain.argmax(0)
        at_old = gain[np.maximum(old, 0), np.arange(len(words))]
        new = np.where(has & (gain[new, np.arange(len(words))] <= at_old + 1e-9), old, new)
        moved = new != old
        if moved.any():
            out = np.flatnonzero(moved & has)
            np.subtract.at(total, old[out], w[out])
            np.add.at(total, new[moved], w[moved])
            entry = np.repeat(moved & has, size)
            np.subtract.at(table, (each[entry], c[entry]), x[entry])
            entry = np.repeat(moved, size)
            np.add.at(table, (np.repeat(new, size)[entry], c[entry]), x[entry])
            np.maximum(table, 0, out=table)
            np.maximum(total, 0, out=total)
            own[words] = new
    return own


def _founders(vocabulary: DataFrame, classes: int) -> list:
    """The `classes` most frequent words and their rows of counts; ties by the word."""

    def top(batches):
        for batch in batches:
            for x in batch.to_pylist():
                words, counts = unpack_words(x["words"]), unpack_array(x["counts"], np.int64)
                length, context, n = _matrix(x)
                ends = np.cumsum(length, dtype=np.int64)
                best = sorted((i for i in np.argsort(-counts, kind="stable")[: classes + 1].tolist() if words[i] != END), key=lambda i: (-counts[i], words[i]))
                # a tie at the end: all words as frequent as the last
                if len(best) > classes:
                    last = counts[best[classes - 1]]
                    best = sorted((i for i in np.flatnonzero(counts >= last).tolist() if words[i] != END), key=lambda i: (-counts[i], words[i]))[:classes]
                for i in best:
                    a, b = ends[i] - length[i], ends[i]
                    yield pa.RecordBatch.from_arrays([pa.array([words[i]], pa.binary()), pa.array([int(counts[i])], pa.int64()), pa.array([context[a:b].astype(np.uint16).tobytes()], pa.binary()), pa.array([n[a:b].astype(np.uint64).tobytes()], pa.binary())], names=["word", "n", "contexts", "sums"])

    each = vocabulary.select("words", "counts", "lens", "contexts", "sums").mapInArrow(top, "word binary, n long, contexts binary, sums binary")
    return each.orderBy(F.col("n").desc(), "word").limit(classes).collect()


def _classes_row(part: int, own: np.ndarray, counts: np.ndarray, classes: int) -> pa.RecordBatch:
    """A part's classes as they're kept (0 is END's alone), and the tokens of each."""
    of = np.where(own < 0, 0, own + 1)
    mass = np.bincount(of, counts, classes + 1)
    return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([pack(of.astype(np.uint16))], pa.binary()), pa.array([mass.tobytes()], pa.binary())], names=["part", "classes", "mass"])


_CLASSES = "part int, classes binary, mass binary"


def found(vocabulary: DataFrame, classes: int = CLASSES) -> DataFrame:
    """(part, classes, mass): the first classes of every word."""
    spark = vocabulary.sparkSession
    founders = _founders(vocabulary, classes)
    table, total = np.zeros((classes, PROVISIONAL)), np.zeros(classes)
    for i, x in enumerate(founders):
        table[i, np.frombuffer(x.contexts, np.uint16)] = np.frombuffer(x.sums, np.uint64)
        total[i] = x.n
    sent = spark.sparkContext.broadcast((table, total, {bytes(x.word): i for i, x in enumerate(founders)}))

    def run(batches):
        for batch in batches:
            for x in batch.to_pylist():
                table, total, seeds = sent.value
                words = unpack_words(x["words"])
                own = np.fromiter((-2 if w == END else seeds.get(w, -1) for w in words), np.int64, len(words))
                own = exchange(*_matrix(x), own, table.copy(), total.copy(), 1)
                yield _classes_row(x["part"], own, unpack_array(x["counts"], np.int64), classes)

    return common.materialise(vocabulary.select("part", "words", "counts", "lens", "contexts", "sums").mapInArrow(run, _CLASSES), "lm-classes")


def _by_part(*tables: DataFrame) -> DataFrame:
    """Rows of all tables by part, those of the first table first: for functions that stream through them. Each has `part`; other columns of the same name are shared."""
    out = None
    for k, x in enumerate(tables):
        x = x.withColumn("kind", F.lit(k))
        out = x if out is None else out.unionByName(x, allowMissingColumns=True)
    return out.repartition("part").sortWithinPartitions("part", "kind")


def _located(batches):
    """kind 0: a part's words; kind 1: what chunks ask -> the words' places in the part."""
    known: dict[bytes, int] = {}
    part = None
    for batch in batches:
        for p, kind, chunk, blob in zip(*(batch.column(batch.schema.get_field_index(c)) for c in ("part", "kind", "chunk", "words"))):
            if p.as_py() != part:
                part, known = p.as_py(), {}
            words = unpack_words(blob.as_py())
            if kind.as_py() == 0:
                known = dict(zip(words, range(len(words))))
                continue
            at = np.fromiter((known.get(w, _MISSING) for w in words), np.int64, len(words)).astype(np.uint32)
            yield pa.RecordBatch.from_arrays([pa.array([chunk.as_py()], pa.int64()), pa.array([part], pa.int32()), pa.array([pack(at)], pa.binary())], names=["chunk", "part", "at"])


def _classed(classes: int):
    """kind 0: a part's classes; kind 1: places asked by chunks -> with their classes, classes + 1 for a word that's missing."""

    def run(batches):
        part, of = None, np.zeros(0, np.uint16)
        for batch in batches:
            for x in batch.to_pylist():
                if x["part"] != part:
                    part, of = x["part"], np.full(1, classes + 1, np.uint16)
                if x["kind"] == 0:
                    of = np.append(unpack_array(x["classes"], np.uint16), np.uint16(classes + 1))
                    continue
                at = np.minimum(unpack_array(x["at"], np.uint32), len(of) - 1)
                yield pa.RecordBatch.from_arrays([pa.array([x["chunk"]], pa.int64()), pa.array([part], pa.int32()), pa.array([x["at"]], pa.binary()), pa.array([pack(of[at])], pa.binary())], names=["chunk", "part", "at", "classes"])

    return run


def _sides(classes: int):
    """Of a chunk and its words' classes: each word's counts by the classes beside it, by part, and the chunk's class pairs."""
    k = classes + 1

    def run(asked: pa.Table, answers: pa.Table) -> pa.Table:
        out = defaultdict(list)
        for x in asked.to_pylist():
            got = {p: (unpack_array(a, np.uint32), unpack_array(c, np.uint16)) for p, a, c in zip(*(answers[n].to_pylist() for n in ("part", "at", "classes")))}
            if got.keys() != set(x["parts"]):
                raise RuntimeError(f"chunk {x['chunk']} lacks answers")
            at = np.concatenate([got[p][0] for p in x["parts"]])
            of = np.concatenate([got[p][1] for p in x["parts"]]).astype(np.int64)
            places, lens = unpack_array(x["places"], np.uint32), unpack_array(x["lens"], np.uint32).astype(np.int64)
            train = np.repeat(unpack_array(x["held"], np.uint8) == 0, lens)
            seq = of[places]
            first = np.zeros(len(seq), bool)
            first[np.cumsum(lens) - lens] = True
            before = np.where(first, 0, np.append(0, seq[:-1]))
            pairs = np.bincount((before * k + seq)[train], minlength=k * k).astype(np.float64)
            words = train & (seq != 0)  # all but END, which a word always comes before
            here = places[words].astype(np.int64) * (2 * k)
            after = np.append(seq[1:], 0)[words]
            key, n = np.unique(np.concatenate([here + before[words], here + k + after]), return_counts=True)
            word = key // (2 * k)
            ends, a, cut = np.cumsum([len(got[p][0]) for p in x["parts"]]).tolist(), 0, 0
            for i, (p, end) in enumerate(zip(x["parts"], ends)):
                stop = int(np.searchsorted(word, end))
                out["part"].append(p)
                out["at"].append(pack(at[a:end]))
                out["lens"].append(pack(np.bincount(word[cut:stop] - a, minlength=end - a).astype(np.uint16)))
                out["contexts"].append(pack((key[cut:stop] % (2 * k)).astype(np.uint16)))
                out["sums"].append(pack(n[cut:stop].astype(np.uint32)))
                out["pairs"].append(None if i else pairs.tobytes())
                a, cut = end, stop
        types = {"part": pa.int32(), "at": pa.binary(), "lens": pa.binary(), "contexts": pa.binary(), "sums": pa.binary(), "pairs": pa.binary()}
        return pa.table({c: pa.array(out[c], t) for c, t in types.items()})

    return run


def _moved(sent, classes: int):
    """kind 0: a part's classes and counts; kind 1: its words' counts by context, chunk by chunk -> new classes."""
    contexts = 2 * (classes + 1)

    def run(batches):
        part, of, counts, keys, sums = None, None, None, [], []

        def fold():
            key, at = np.unique(np.concatenate(keys), return_inverse=True)
            keys[:], sums[:] = [key], [np.bincount(at, np.concatenate(sums), len(key))]

        def done():
            keys.append(np.zeros(0, np.int64))
            sums.append(np.zeros(0))
            fold()
            table, total = sent.value
            length = np.bincount(keys[0] // contexts, minlength=len(of))
            own = exchange(length, keys[0] % contexts, sums[0], of.astype(np.int64) - 1 - (of == 0), table.copy(), total.copy(), 2)
            return _classes_row(part, own, counts, classes)

        for batch in batches:
            for x in batch.to_pylist():
                if x["part"] != part:
                    if part is not None:
                        yield done()
                    part, keys, sums = x["part"], [], []
                if x["kind"] == 0:
                    of, counts = unpack_array(x["classes"], np.uint16), unpack_array(x["counts"], np.int64)
                    continue
                index = unpack_array(x["at"], np.uint32).astype(np.int64)
                keys.append(np.repeat(index, unpack_array(x["lens"], np.uint16)) * contexts + unpack_array(x["contexts"], np.uint16))
                sums.append(unpack_array(x["sums"], np.uint32).astype(np.float64))
                if len(keys) > 8 and sum(map(len, keys[1:])) > len(keys[0]):
                    fold()
        if part is not None:
            yield done()

    return run


def again(chunks: DataFrame, located: DataFrame, vocabulary: DataFrame, own: DataFrame, classes: int) -> tuple[DataFrame, float]:
    """A pass: contexts by the classes `own`, counted anew, and every word moved. Returns the classes and the criterion before the pass."""
    spark, k = chunks.sparkSession, classes + 1
    asked = _by_part(own.select("part", "classes"), located)
    answers = asked.select("part", "kind", "chunk", "at", "classes").mapInArrow(_classed(classes), "chunk long, part int, at binary, classes binary")
    sides = chunks.select("chunk", "held", "lens", "places", "parts").groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(_sides(classes), "part int, at binary, lens binary, contexts binary, sums binary, pairs binary")
    path = common.write(sides, "lm-contexts")
    sides = spark.read.schema(sides.schema).parquet(path)
    pairs = _total(sides.where("pairs is not null").select("pairs"), "pairs", np.float64, k * k).reshape(k, k)
    table = np.hstack([pairs.T[1:], pairs[1:]])  # by the class before, and by the class after
    total = pairs.sum(0)[1:]
    sent = spark.sparkContext.broadcast((table, total))
    held = own.select("part", "classes").join(vocabulary.select("part", "counts"), "part")
    rows = _by_part(held, sides.drop("pairs")).select("part", "kind", "classes", "counts", "at", "lens", "contexts", "sums")
    moved = common.materialise(rows.mapInArrow(common.trimmed(_moved(sent, classes)), _CLASSES), "lm-classes")
    common.remove(spark, path)
    return moved, criterion(table, total, 2)


def _total(tables: DataFrame, column: str, dtype, size: int = 512) -> np.ndarray:
    """The sum of arrays of one fixed size: eight tasks first, then the driver."""

    def add(batches):
        total = None
        for batch in batches:
            for x in batch.column(0).to_pylist():
                x = np.frombuffer(x, dtype)
                total = x.copy() if total is None else total + x
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["total"])

    found = tables.select(column).repartition(8).mapInArrow(add, "total binary").collect()
    return np.sum([np.frombuffer(x.total, dtype) for x in found], axis=0) if found else np.zeros(size, dtype)


class Smoothed:
    """Transitions and emissions, from the counts of class pairs and of what's seen once."""

    def __init__(self, pairs: np.ndarray, once_after: np.ndarray, class_tokens: np.ndarray):
        n = max(1.0, pairs.sum())
        unknown = once_after.sum() / n
        after = pairs.sum(1)
        p_unknown = np.minimum(0.9, (once_after + 20 * unknown + 1e-6) / (after + 20))
        prior = (class_tokens + 1e-3) / (class_tokens + 1e-3).sum()
        step = (pairs + 20 * prior) / (after + 20)[:, None]
        self.step = np.log10(step * (1 - p_unknown)[:, None])
        self.unknown = np.log10(p_unknown)
        # an unseen word comes before what any word comes before
        free = min(0.9, unknown + 1e-6)
        self.step = np.vstack([self.step, np.log10(prior * (1 - free))])
        self.unknown = np.append(self.unknown, np.log10(free))

    def score(self, before: np.ndarray, of: np.ndarray) -> np.ndarray:
        """log10 of the class (the last: unknown) of each token after that before it."""
        k = self.step.shape[1]
        return np.where(of == k, self.unknown[before], self.step[before, np.minimum(of, k - 1)])


def _coded(tokens: int, types: int, classes: int):
    """Of a chunk and the answers of the parts: for each document its counts, sums and class sequence."""

    def run(asked: pa.Table, answers: pa.Table) -> pa.Table:
        out = defaultdict(list)
        for x in asked.to_pylist():
            got = {p: (c, n) for p, c, n in zip(*(answers[k].to_pylist() for k in ("part", "classes", "counts")))}
            if got.keys() != set(x["parts"]):
                raise RuntimeError(f"chunk {x['chunk']} lacks answers")
            of = np.concatenate([unpack_array(got[p][0], np.uint16) for p in x["parts"]])
            pair = np.concatenate([unpack_array(got[p][1], np.float64).reshape(2, -1) for p in x["parts"]], axis=1)
            c, emit = pair
            base = np.log10((c + 1) / (tokens + types + 1))
            places = unpack_array(x["places"], np.uint32)
            lens = unpack_array(x["lens"], np.uint32).astype(np.int64)
            starts = np.cumsum(lens) - lens
            seq = of[places]
            out["doc_id"] += x["docs"]
            out["held_out"] += unpack_array(x["held"], np.uint8).astype(bool).tolist()
            out["n_tokens"] += lens.tolist()
            out["n_known"] += np.add.reduceat((c > 0).astype(np.int64)[places], starts).tolist()
            out["base_score"] += np.add.reduceat(base[places], starts).tolist()
            out["emission"] += np.add.reduceat(emit[places], starts).tolist()
            code = (seq | np.where(c == 1, 0x8000, 0).astype(np.uint16)[places]).tobytes()
            out["classes"] += [code[2 * a : 2 * b] for a, b in zip(starts.tolist(), (starts + lens).tolist())]
        types_ = {"doc_id": pa.int64(), "held_out": pa.bool_(), "n_tokens": pa.int64(), "n_known": pa.int64(), "base_score": pa.float64(), "emission": pa.float64(), "classes": pa.binary()}
        return pa.table({k: pa.array(out[k], t) for k, t in types_.items()})

    return run


def _answers(class_tokens, classes: int):
    """kind 0: a part's counts and classes; kind 1: places asked by chunks -> class, and (count, log10 emission)."""

    def run(batches):
        part = None
        for batch in batches:
            for x in batch.to_pylist():
                if x["part"] != part:
                    part, of, n, emit = x["part"], np.full(1, classes + 1, np.uint16), np.zeros(1), np.zeros(1)
                if x["kind"] == 0:
                    of, n = unpack_array(x["classes"], np.uint16), unpack_array(x["counts"], np.int64)
                    emit = np.append(np.log10(n / np.maximum(1, class_tokens.value[of])), 0.0)
                    of, n = np.append(of, np.uint16(classes + 1)), np.append(n, 0).astype(np.float64)
                    continue
                at = np.minimum(unpack_array(x["at"], np.uint32), len(of) - 1)
                yield pa.RecordBatch.from_arrays([pa.array([x["chunk"]], pa.int64()), pa.array([part], pa.int32()), pa.array([pack(of[at])], pa.binary()), pa.array([pack(np.concatenate([n[at], emit[at]]))], pa.binary())], names=["chunk", "part", "classes", "counts"])

    return run


def _asked(batches):
    for batch in batches:
        for x in batch.to_pylist():
            n = len(x["parts"])
            yield pa.RecordBatch.from_arrays([pa.array([x["chunk"]] * n, pa.int64()), pa.array(x["parts"], pa.int32()), pa.array(x["words"], pa.binary())], names=["chunk", "part", "words"])


def _given(batches):
    for batch in batches:
        for x in batch.to_pylist():
            yield pa.RecordBatch.from_arrays([pa.array(x["parts"], pa.int32()), pa.array(x["words"], pa.binary()), pa.array(x["counts"], pa.binary()), pa.array(x["rows"], pa.binary())], names=["part", "words", "counts", "rows"])


class Learned:
    """What a table of documents gives: vocabulary (part, words, counts, ..) and classes (part, classes, mass) in parts, sums, and the model."""

    vocabulary: DataFrame
    classes: DataFrame
    tokens: int
    types: int
    class_tokens: np.ndarray
    model: Smoothed
    #: The criterion before each pass.
    criteria: list[float]


def word_classes(learned: Learned) -> DataFrame:
    """(word, n, class) of the vocabulary."""

    def run(batches):
        for batch in batches:
            for x in batch.to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array(unpack_words(x["words"]), pa.binary()), pa.array(unpack_array(x["counts"], np.int64)), pa.array(unpack_array(x["classes"], np.uint16).astype(np.int32))], names=["word", "n", "class"])

    both = learned.vocabulary.select("part", "words", "counts").join(learned.classes.select("part", "classes"), "part")
    return both.mapInArrow(run, "word binary, n long, class int")


def score(df: DataFrame, held_out: Column, doc_id: str = "doc_id", text: str = "text", classes: int = CLASSES, passes: int = PASSES, chunk_chars: int = CHUNK_CHARS) -> DataFrame:
    """Learns from df's rows where held_out is false and scores all: (doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, perplexity)."""
    return learn_and_score(df, held_out, doc_id, text, classes, passes, chunk_chars)[1]


def learn_and_score(df: DataFrame, held_out: Column, doc_id: str = "doc_id", text: str = "text", classes: int = CLASSES, passes: int = PASSES, chunk_chars: int = CHUNK_CHARS) -> tuple[Learned, DataFrame]:
    spark, out = df.sparkSession, Learned()
    parts = min(MOST_PARTS, common.shuffle_parts(spark))
    rows = df.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held_out"), F.col(text).alias("text"))
    chunk_path = common.write(rows.mapInArrow(_chunks(parts, chunk_chars), _CHUNK), "lm-chunks")
    chunks = spark.read.schema(_CHUNK).parquet(chunk_path)
    given = chunks.select("parts", "words", "counts", "rows").mapInArrow(_given, "part int, words binary, counts binary, rows binary")
    summed = given.repartition("part").sortWithinPartitions("part").mapInArrow(_summed, "part int, words binary, counts binary, lens binary, contexts binary, sums binary, tokens long, types long")
    out.vocabulary = vocabulary = common.materialise(summed, "lm-vocabulary")
    out.tokens, out.types = tokens, types = tuple(x or 0 for x in vocabulary.agg(F.sum("tokens"), F.sum("types")).first())
    asked = chunks.select("chunk", "parts", "words").mapInArrow(_asked, "chunk long, part int, words binary")
    located = _by_part(vocabulary.select("part", "words"), asked).select("part", "kind", "chunk", "words").mapInArrow(_located, "chunk long, part int, at binary")
    located_path = common.write(located, "lm-places")
    located = spark.read.schema(located.schema).parquet(located_path)
    own, out.criteria = found(vocabulary, classes), []
    for _ in range(passes if tokens else 0):
        own, before = again(chunks, located, vocabulary, own, classes)
        out.criteria.append(before)
    out.classes = own
    out.class_tokens = class_tokens = _total(own.select("mass"), "mass", np.float64, classes + 1)
    sent_tokens = spark.sparkContext.broadcast(class_tokens)
    held = own.select("part", "classes").join(vocabulary.select("part", "counts"), "part")
    answers = _by_part(held, located).select("part", "kind", "chunk", "at", "classes", "counts").mapInArrow(_answers(sent_tokens, classes), "chunk long, part int, classes binary, counts binary")
    coded = chunks.select("chunk", "docs", "held", "lens", "places", "parts").groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(_coded(tokens, types, classes), "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, emission double, classes binary")
    coded = common.materialise(coded, "lm-coded")
    for path in (chunk_path, located_path):
        common.remove(spark, path)

    def pairs(batches):
        """Class pairs of the training texts, and what's seen once after each class."""
        k = classes + 1
        n, once = np.zeros(k * k), np.zeros(k)
        for batch in batches:
            for blob in batch.column(0).to_pylist():
                code = np.frombuffer(blob, np.uint16)
                of = (code & 0x7FFF).astype(np.int64)
                before = np.append(0, of[:-1])
                n += np.bincount(before * k + of, minlength=k * k) if len(of) > k * k else 0
                if len(of) <= k * k:
                    np.add.at(n, before * k + of, 1)
                np.add.at(once, before[code >> 15 == 1], 1)
        yield pa.RecordBatch.from_arrays([pa.array([np.concatenate([n, once]).tobytes()], pa.binary())], names=["n"])

    k = classes + 1
    counted = _total(coded.where("not held_out").select("classes").mapInArrow(pairs, "n binary"), "n", np.float64) if tokens else np.zeros(k * k + k)
    out.model = Smoothed(counted[: k * k].reshape(k, k), counted[k * k :], class_tokens)
    model = spark.sparkContext.broadcast(out.model)

    def final(batches):
        for batch in batches:
            total = []
            for blob, emission in zip(batch.column(6).to_pylist(), batch.column(5).to_pylist()):
                of = (np.frombuffer(blob, np.uint16) & 0x7FFF).astype(np.int64)
                total.append(float(model.value.score(np.append(0, of[:-1]), of).sum()) + emission if tokens else 0.0)
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(total, pa.float64())], names=["doc_id", "held_out", "n_tokens", "n_known", "base_score", "score"])

    done = coded.mapInArrow(final, "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    return out, done.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(tokens).cast("long").alias("train_tokens"), "base_score", "score", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")).alias("perplexity"))


def op3_brown_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .language_id import remainder

    return score(common.table(spark, sf_dir, "documents"), remainder(F.col("doc_id"), 7) == 2)
