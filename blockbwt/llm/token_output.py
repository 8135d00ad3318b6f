"""Operator 1: token ids in files with Elias-Fano document boundaries.

A file's row is a segment: the ids of consecutive documents concatenated at the
narrowest fixed width that holds the vocabulary, the boundaries of the documents
and their doc_ids as Elias-Fano sequences with select, and where in its
partition it begins. Segments are cut at SEGMENT_TOKENS ids (one document is
never cut), so a writer holds one segment. Spark's own writer puts them into
Parquet files: its commit protocol survives lost executors, and any store that
Spark reaches will do. Partitions are ranges of doc_id, in order.

Texts are encoded as the library does by default: the name of a special token in
a text is that token. `special_as_text` makes it ordinary text.

Ranges are cut by (doc_id, hash of the text, place of the row in the input), so
rows of one id, null ones included, and rows that repeat are spread over tasks.

Defined results: a null or empty text has the end id alone; null doc_ids come
first, then equal doc_ids by their texts' hashes and texts; repeated rows are all
written; an empty table gives no segment and no row.
"""

from __future__ import annotations

import os
import re
import zlib
from collections import defaultdict
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .elias_fano import EliasFano

SEGMENT_TOKENS = 1 << 20
SEGMENT = "part int, seq int, base long, n_docs int, n_tokens long, width int, n_null int, doc_ids binary, bounds binary, ids binary"
ROWS = "doc_id long, start long, n_tokens long, ids_crc32 long"

#: A space between two characters that aren't white space always begins a
#: pre-token of a byte-level BPE: texts may be encoded piece by piece there.
_AT_SPACE, _BLANKS = re.compile(r"(?<=\S) (?=\S)"), re.compile(r"\s\s")
_encoders: dict[tuple[str, bool], PieceEncoder] = {}


class PieceEncoder:
    """The tokenizers library, asked once for each distinct piece that it holds.

    max_pieces bounds what is held; beyond it the store is begun anew, which
    changes no result.
    """

    def __init__(self, vocabulary: str, special_as_text: bool = False, max_pieces: int = 1_000_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(vocabulary)
        self.tokenizer.encode_special_tokens = special_as_text
        names = self.tokenizer.get_vocab()
        self.kind = np.dtype("<u4" if max(names.values()) >> 16 else "<u2")
        self.sizes = np.zeros(max(names.values()) + 1, np.int64)
        self.sizes[list(names.values())] = list(map(len, names))  # a character of a byte-level token is a byte
        self.max_pieces = max_pieces
        self._forget()

    def _forget(self) -> None:
        self.place: dict[str, int] = defaultdict()
        self.place.default_factory = self.place.__len__
        self.ids: list[bytes] = []

    @classmethod
    def of(cls, vocabulary: str, special_as_text: bool = False) -> PieceEncoder:
        if (key := (vocabulary, special_as_text)) not in _encoders:
            _encoders[key] = cls(vocabulary, special_as_text)
        return _encoders[key]

    def _whole(self, texts: list[str]) -> list[np.ndarray]:
        return [np.asarray(e.ids, self.kind) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, pieces: list[str]) -> None:
        """Pieces that follow a space. Those that neither begin nor end with white space are encoded many in a text, and told apart by the bytes of their tokens."""
        ids: list[bytes] = [b""] * len(pieces)
        plain = [i for i, x in enumerate(pieces) if x and not x[0].isspace() and not x[-1].isspace()]
        alone = [i for i, x in enumerate(pieces) if not x or x[0].isspace() or x[-1].isspace()]
        for at in range(0, len(plain), 20_000):
            runs = [plain[k : k + 250] for k in range(at, min(at + 20_000, len(plain)), 250)]
            for run, got in zip(runs, self._whole([" " + " ".join([pieces[i] for i in run]) for run in runs])):
                ends = np.cumsum([len(pieces[i].encode()) + 1 for i in run])
                cuts = np.searchsorted(np.cumsum(self.sizes[got]), ends) + 1
                raw, a = got.tobytes(), 0
                for i, b in zip(run, (cuts * self.kind.itemsize).tolist()):
                    ids[i] = raw[a:b]
                    a = b
        for i, got in zip(alone, self._whole([" " + pieces[i] for i in alone])):
            ids[i] = got.tobytes()
        self.ids += ids

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text, little-endian, two or four bytes each."""
        if len(self.ids) > self.max_pieces:
            self._forget()
        split = [_AT_SPACE.split(x) if _BLANKS.search(x) else x.split(" ") for x in texts]
        place = self.place.__getitem__
        places = [list(map(place, x[1:])) for x in split]
        if len(self.place) > len(self.ids):
            self._learn(list(islice(self.place, len(self.ids), None)))
        get = self.ids.__getitem__
        return [first.tobytes() + b"".join(map(get, x)) for first, x in zip(self._whole([x[0] for x in split]), places)]


def _groups(batch: list[str], most: int = 1 << 21) -> Iterator[list[str]]:
    """Runs of texts of about `most` characters, to bound what one call holds."""
    group, size = [], 0
    for text in batch:
        group.append(text)
        size += len(text)
        if size >= most:
            yield group
            group, size = [], 0
    if group:
        yield group


def write_segments(df: DataFrame, path: str, vocabulary: str, doc_id: str = "doc_id", text: str = "text", end_id: int = 0, segment_tokens: int = SEGMENT_TOKENS, special_as_text: bool = False) -> None:
    """Encodes `text` and writes the files at `path`, in ascending order of `doc_id`."""

    def encode(batches):
        encoder, part, seq, base = PieceEncoder.of(vocabulary, special_as_text), TaskContext.get().partitionId(), 0, 0
        kind = encoder.kind
        end = int(end_id).to_bytes(kind.itemsize, "little")
        docs, parts, lens, held = [], [], [], 0

        def segment():
            nonlocal seq, base
            nulls = sum(x is None for x in docs)
            bounds = np.concatenate([[0], np.cumsum(np.asarray(lens, np.int64))])
            row = {"part": part, "seq": seq, "base": base, "n_docs": len(docs), "n_tokens": int(bounds[-1]), "width": kind.itemsize, "n_null": nulls, "doc_ids": EliasFano.encode(docs[nulls:]).to_bytes(), "bounds": EliasFano.encode(bounds).to_bytes(), "ids": b"".join(parts)}
            seq, base = seq + 1, base + row["n_tokens"]
            for x in (docs, parts, lens):
                x.clear()
            return pa.RecordBatch.from_pylist([row], schema)

        for batch in batches:
            ids = iter(batch.column(0).to_pylist())
            for group in _groups([x or "" for x in batch.column(1).to_pylist()]):
                for got in encoder.encode(group):
                    docs.append(next(ids))
                    parts += (got, end)
                    lens.append(len(got) // kind.itemsize + 1)
                    held += lens[-1]
                    if held >= segment_tokens:
                        yield segment()
                        held = 0
        if docs:
            yield segment()

    schema = pa.schema([("part", pa.int32()), ("seq", pa.int32()), ("base", pa.int64()), ("n_docs", pa.int32()), ("n_tokens", pa.int64()), ("width", pa.int32()), ("n_null", pa.int32()), ("doc_ids", pa.binary()), ("bounds", pa.binary()), ("ids", pa.binary())])
    rows = df.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"), F.xxhash64(F.col(text)).alias("h"), F.monotonically_increasing_id().alias("row"))
    ordered = rows.repartitionByRange("doc_id", "h", "row").sortWithinPartitions("doc_id", "h", "text")
    ordered.select("doc_id", "text").mapInArrow(encode, SEGMENT).write.mode("overwrite").option("compression", "zstd").parquet(path)


def read_segments(spark: SparkSession, path: str) -> DataFrame:
    """The segments with `start`: the ids before each. The sums are over partitions, of which the writer's shuffle has a bounded number."""
    segments = spark.read.schema(SEGMENT).parquet(path)
    totals = sorted(map(tuple, segments.groupBy("part").agg(F.sum("n_tokens")).collect()))
    befores = np.cumsum([0, *(n for _, n in totals)]).tolist()
    starts = spark.createDataFrame([(p, b) for (p, _), b in zip(totals, befores)], "part int, before long")
    return segments.join(F.broadcast(starts), "part").withColumn("start", F.col("before") + F.col("base"))


def read_documents(spark: SparkSession, path: str) -> DataFrame:
    """A row for each document, from the files alone."""

    def decode(batches):
        for batch in batches:
            for x in batch.to_pylist():
                bounds = EliasFano.from_bytes(x["bounds"]).all()
                ids = np.frombuffer(x["ids"], f"<u{x['width']}").astype("<u4")
                docs = [None] * x["n_null"] + EliasFano.from_bytes(x["doc_ids"]).all().tolist()
                view = memoryview(ids).cast("B")
                crc = [zlib.crc32(view[4 * a : 4 * b]) for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist())]
                yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(x["start"] + bounds[:-1]), pa.array(np.diff(bounds)), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    wanted = read_segments(spark, path).select("start", "width", "n_null", "doc_ids", "bounds", "ids")
    return wanted.mapInArrow(decode, ROWS)


def document_ids(segment: dict, i: int) -> np.ndarray:
    """The ids of document i of a segment, by two selects."""
    bounds = EliasFano.from_bytes(segment["bounds"])
    a, b = bounds.select(i), bounds.select(i + 1)
    return np.frombuffer(segment["ids"], f"<u{segment['width']}", b - a, a * segment["width"]).astype(np.uint32)


def find_documents(spark: SparkSession, path: str, doc_ids: list[int]) -> DataFrame:
    """(doc_id, start, ids) of the rows with one of some doc_ids: searches by select in each segment, whose other documents aren't read."""
    wanted = sorted(set(doc_ids))

    def run(batches):
        for batch in batches:
            for x in batch.to_pylist():
                held, bounds = EliasFano.from_bytes(x["doc_ids"]), EliasFano.from_bytes(x["bounds"])
                found = [(d, x["n_null"] + i) for d in wanted for i in range(held.rank(d), held.rank(d + 1))]
                ids = [document_ids(x, i).tolist() for _, i in found]
                starts = [x["start"] + bounds.select(i) for _, i in found]
                yield pa.RecordBatch.from_arrays([pa.array([d for d, _ in found], pa.int64()), pa.array(starts, pa.int64()), pa.array(ids, pa.list_(pa.int64()))], names=["doc_id", "start", "ids"])

    segments = read_segments(spark, path).select("start", "width", "n_null", "doc_ids", "bounds", "ids")
    return segments.mapInArrow(run, "doc_id long, start long, ids array<bigint>")


def document_at(segment: dict, offset: int) -> int:
    """Which document of a segment (from 0) holds the id at an offset into it."""
    bounds = EliasFano.from_bytes(segment["bounds"])
    if not 0 <= offset < segment["n_tokens"]:
        raise IndexError(offset)
    return bounds.rank(offset + 1) - 1


def op1_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = common.scratch_path(spark, "tokens")
    write_segments(common.table(spark, sf_dir, "documents"), path, public_tokenizers.path("byte_bpe_50k.json"))
    return read_documents(spark, path)
