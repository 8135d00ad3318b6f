"""Operator 2: byte-level BPE over one global shuffle of distinct words.

Documents are read once into chunks of about CHUNK_CHARS characters. A chunk
keeps the place of every pre-token as an index into its own dictionary, so a
position costs about two bytes instead of a row. The dictionary's words are
dealt by their hash to parts; a part encodes each distinct word once, whatever
number of chunks asks, and answers with ids, which come back to the chunk by its
number and are put together by position. A word is asked for at most once by a
chunk, so a very common word is no hot key. The chunks' exchange feeds both the
words and the reassembly, and is written once.

Decoding joins a token-byte table (token_id, token_bytes), a DataFrame. One whose
counted size is at most MOST_TOKENS rows and MOST_TOKEN_BYTES is joined where the
ids are, from a broadcast; a larger one is joined by a shuffle of ids with their
places, and put together by position in pieces of PIECE ids.

There are MOST_PARTS parts at most, so that what a chunk asks of each doesn't
shrink to nothing as chunks and parts grow together; a part's words are its share
of the vocabulary.

Defined results: a null or empty text has no ids and decodes to nothing; rows
with a null or repeated doc_id are encoded like any others, one result a row; an
empty table gives no row. A lone very long text makes a chunk of its own.
"""

from __future__ import annotations

import base64
import itertools
import re
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .common import pack, pack_words, unpack_array, unpack_words

CHUNK_CHARS, MOST_PARTS = 6 << 20, 1024
MOST_TOKENS, MOST_TOKEN_BYTES, PIECE = 4 << 20, 64 << 20, 4096
CHUNK = "chunk long, docs array<long>, doc_pieces binary, places binary, piece_words binary, word_places binary, parts array<int>, words array<binary>"
_AT_SPACE, _BLANKS = re.compile(r"(?<=\S) (?=\S)"), re.compile(r"\s\s")
_loaded: dict[str, object] = {}


def ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


def encoding(path: str, pattern: str):
    if path not in _loaded:
        import tiktoken

        _loaded[path] = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks(path), special_tokens={})
    return _loaded[path]


def token_table(spark: SparkSession, path: str) -> DataFrame:
    """(token_id, token_bytes) of a file of ranks, which the driver reads."""
    return spark.createDataFrame([(i, token) for token, i in ranks(path).items()], "token_id int, token_bytes binary")


def deal(words: list[bytes], parts: int) -> tuple[np.ndarray, list[int], list[bytes]]:
    """Words by part: the new index of each word, the parts that have words, and their packed words. Indices count through the parts in order."""
    of = np.fromiter((zlib.crc32(w) % parts for w in words), np.int64, len(words))
    order = np.argsort(of, kind="stable")
    index = np.empty(len(words), np.uint32)
    index[order] = np.arange(len(words), dtype=np.uint32)
    used, begins = np.unique(of[order], return_index=True)
    blobs = [pack_words([words[i] for i in order[a:b].tolist()]) for a, b in zip(begins, [*begins[1:], len(words)])]
    return index, used.tolist(), blobs


def _chunks(pattern: str, parts: int, most: int):
    def run(batches):
        import regex

        find, task, seq = regex.compile(pattern).findall, TaskContext.get().partitionId(), 0
        docs, counts, places, held = [], [], [], 0

        def begin():
            nonlocal number, first, after, held
            number = itertools.count().__next__
            first, after, held = defaultdict(number), defaultdict(number), 0

        number = first = after = None
        begin()

        def chunk():
            nonlocal seq
            pieces = [""] * (len(first) + len(after))
            for x, i in first.items():
                pieces[i] = x
            for x, i in after.items():
                pieces[i] = " " + x
            words: dict[str, int] = defaultdict()
            words.default_factory = words.__len__
            split = [find(x) for x in pieces]
            flat = np.fromiter(map(words.__getitem__, itertools.chain.from_iterable(split)), np.uint32)
            index, used, blobs = deal([w.encode() for w in words], parts)
            row = {"chunk": task << 32 | seq, "docs": docs, "doc_pieces": pack(np.asarray(counts, np.uint32)), "places": pack(np.concatenate(places)), "piece_words": pack(np.fromiter(map(len, split), np.uint32, len(split))), "word_places": pack(index[flat]), "parts": used, "words": blobs}
            seq += 1
            out = pa.RecordBatch.from_pylist([row], schema)
            for x in (docs, counts, places):
                x.clear()
            begin()
            return out

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                text = text.as_py() or ""
                split = _AT_SPACE.split(text) if _BLANKS.search(text) else text.split(" ")
                place = np.empty(len(split), np.uint32)
                place[0] = first[split[0]]
                place[1:] = np.fromiter(map(after.__getitem__, itertools.islice(split, 1, None)), np.uint32, len(split) - 1)
                docs.append(doc)
                counts.append(len(split))
                places.append(place)
                held += len(text) + 16
                if held >= most:
                    yield chunk()
        if docs:
            yield chunk()

    schema = pa.schema([("chunk", pa.int64()), ("docs", pa.list_(pa.int64())), ("doc_pieces", pa.binary()), ("places", pa.binary()), ("piece_words", pa.binary()), ("word_places", pa.binary()), ("parts", pa.list_(pa.int32())), ("words", pa.list_(pa.binary()))])
    return run


def _asked(batches):
    """A row for each chunk and part."""
    for batch in batches:
        for x in batch.to_pylist():
            yield pa.RecordBatch.from_arrays([pa.array([x["chunk"]] * len(x["parts"]), pa.int64()), pa.array(x["parts"], pa.int32()), pa.array(x["words"], pa.binary())], names=["chunk", "part", "words"])


def _answered(path: str, pattern: str):
    """Rows come by part, so that a part's distinct words are all that is held."""

    def run(batches):
        encode, part, known = encoding(path, pattern)._encode_single_piece, None, {}
        for batch in batches:
            ids = []
            for p, blob in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                if p != part:
                    part, known = p, {}
                words = unpack_words(blob)
                for w in words:
                    if w not in known:
                        known[w] = np.asarray(encode(w), np.uint32).tobytes()
                ids.append(pack_words([known[w] for w in words]))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(ids, pa.binary())], names=["chunk", "part", "ids"])

    return run


def _reassembled(asked: pa.Table, answers: pa.Table) -> pa.Table:
    docs, out = [], []
    for x in asked.to_pylist():
        got = dict(zip(answers["part"].to_pylist(), answers["ids"].to_pylist()))
        if got.keys() != set(x["parts"]):
            raise RuntimeError(f"chunk {x['chunk']} has other words than were encoded; its input isn't deterministic")
        word = list(itertools.chain.from_iterable(unpack_words(got[p]) for p in x["parts"]))
        words = list(map(word.__getitem__, unpack_array(x["word_places"], np.uint32).tolist()))
        ends = np.cumsum(unpack_array(x["piece_words"], np.uint32), dtype=np.int64).tolist()
        piece = [b"".join(words[a:b]) for a, b in zip([0, *ends], ends)]
        pieces = list(map(piece.__getitem__, unpack_array(x["places"], np.uint32).tolist()))
        ends = np.cumsum(unpack_array(x["doc_pieces"], np.uint32), dtype=np.int64).tolist()
        docs += x["docs"]
        out += [b"".join(pieces[a:b]) for a, b in zip([0, *ends], ends)]
    return pa.table({"doc_id": pa.array(docs, pa.int64()), "ids": pa.array(out, pa.binary())})


def _chunk_done(asked: pa.Table, answers: pa.Table) -> pa.Table:
    out = _reassembled(asked, answers)
    common.release()
    return out


def encode(df: DataFrame, ranks_path: str, pattern: str, doc_id: str = "doc_id", text: str = "text", chunk_chars: int = CHUNK_CHARS, parts: int | None = None) -> DataFrame:
    """(doc_id, ids): ids as little-endian unsigned 32-bit integers, one row for each row of df."""
    common.small_batches(df.sparkSession)
    parts = parts or min(MOST_PARTS, common.shuffle_parts(df.sparkSession))
    rows = df.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    chunks = rows.mapInArrow(common.trimmed(_chunks(pattern, parts, chunk_chars)), CHUNK).repartition("chunk")
    asked = chunks.mapInArrow(_asked, "chunk long, part int, words binary")
    answers = asked.repartition("part").sortWithinPartitions("part").mapInArrow(common.trimmed(_answered(ranks_path, pattern)), "chunk long, part int, ids binary")
    return chunks.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(_chunk_done, "doc_id long, ids binary")


def decode(df: DataFrame, tokens: DataFrame, doc_id: str = "doc_id", ids: str = "ids", most_tokens: int = MOST_TOKENS) -> DataFrame:
    """(doc_id, ids, decoded): the bytes of the ids, a left join with tokens (token_id, token_bytes); ids that no token has give no bytes, null ids give null."""
    given = df.select(F.col(doc_id).alias("doc_id"), F.col(ids).alias("ids"))
    n, size, last, first = tokens.agg(F.count(F.lit(1)), F.sum(F.octet_length("token_bytes")), F.max("token_id"), F.min("token_id")).first()
    if n > most_tokens or (size or 0) > MOST_TOKEN_BYTES or (last or 0) > most_tokens or (first or 0) < 0:
        return _decode_by_shuffle(given, tokens)
    table = [b""] * ((last or 0) + 1)
    for x in tokens.collect():
        if x.token_id is not None:
            table[x.token_id] = bytes(x.token_bytes or b"")
    sent = df.sparkSession.sparkContext.broadcast(table)

    def run(batches):
        table = sent.value
        known = len(table)
        for batch in (x for whole in batches for x in common.slices(whole, 1, 1 << 22)):
            out = []
            for x in batch.column(1).to_pylist():
                at = np.frombuffer(x or b"", "<u4")
                if len(at) and at.max() >= known:
                    at = at[at < known]
                out.append(None if x is None else b"".join(map(table.__getitem__, at.tolist())))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.binary())], names=["doc_id", "ids", "decoded"])

    return given.mapInArrow(common.trimmed(run), "doc_id long, ids binary, decoded binary")


def _decode_by_shuffle(given: DataFrame, tokens: DataFrame) -> DataFrame:
    """For tables of any size: ids with their places are joined, put together piece by piece, and the pieces by document."""
    rows = common.materialise(given.withColumn("row", F.monotonically_increasing_id()), "ids")
    n = F.expr("cast(octet_length(ids) div 4 as int)")
    places = rows.where(n > 0).select("row", "ids", F.explode(F.sequence(F.lit(0), n - 1)).alias("place"))
    number = F.conv(F.array_join(F.array(*[F.hex(F.expr(f"substring(ids, place * 4 + {k}, 1)")) for k in (4, 3, 2, 1)]), ""), 16, 10).cast("long")
    asked = places.select("row", "place", number.alias("token_id"))
    met = asked.join(tokens.select(F.col("token_id").cast("long").alias("token_id"), "token_bytes"), "token_id")
    piece = met.groupBy("row", F.floor(F.col("place") / PIECE).alias("piece")).agg(F.array_sort(F.collect_list(F.struct("place", F.hex("token_bytes").alias("b")))).alias("s"))
    said = piece.select("row", "piece", F.array_join(F.transform("s", lambda x: x["b"]), "").alias("t"))
    whole = said.groupBy("row").agg(F.array_sort(F.collect_list(F.struct("piece", "t"))).alias("s"))
    joined = rows.join(whole.select("row", F.unhex(F.array_join(F.transform("s", lambda x: x["t"]), "")).alias("decoded")), "row", "left")
    return joined.select("doc_id", "ids", F.when(F.col("ids").isNotNull(), F.coalesce("decoded", F.lit(b""))).alias("decoded"))


def digests(docs: DataFrame) -> DataFrame:
    import public_tokenizers

    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    done = decode(encode(docs, path, public_tokenizers.PATTERN), token_table(docs.sparkSession, path))
    return done.select("doc_id", F.expr("cast(octet_length(ids) div 4 as long)").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(common.table(spark, sf_dir, "documents"))
