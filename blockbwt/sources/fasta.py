"""Read files: FASTA and FASTQ as Python data sources that split by bytes, and writers."""

from __future__ import annotations

import gzip
import os
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "header string, s string"


class _Span(InputPartition):
    def __init__(self, path: str, begin: int, end: int):
        self.path, self.begin, self.end = path, begin, end


def _files(path: str) -> list[str]:
    if os.path.isdir(path):
        return sorted(os.path.join(path, x) for x in os.listdir(path) if not x.startswith(("_", ".")))
    return [path]


def _open(path: str):
    return gzip.open(path, "rb") if path.endswith(".gz") else open(path, "rb")


class _FastaReader(DataSourceReader):
    """A span has the records that begin in it. Compressed files can't be split: one span each."""

    def __init__(self, path: str, span: int):
        self.path, self.span = path, span

    def partitions(self):
        out = []
        for f in _files(self.path):
            size = os.path.getsize(f)
            step = size + 1 if f.endswith(".gz") else self.span
            out += [_Span(f, a, min(a + step, size) if not f.endswith(".gz") else 1 << 62) for a in range(0, max(1, size), step)]
        return out or [_Span("", 0, 0)]

    def read(self, part: _Span) -> Iterator[tuple]:
        if not part.path:
            return
        with _open(part.path) as f:
            at, header, lines = part.begin, None, []
            if at:
                f.seek(at - 1)
                at += len(f.readline()) - 1  # the line that the span begins in is the span's before
            for line in f:
                if line.startswith(b">"):
                    if header is not None:
                        yield header, b"".join(lines).decode()
                        header, lines = None, []
                    if at >= part.end:
                        return
                    header = line[1:].strip().decode()
                elif header is not None:
                    lines.append(line.strip())
                at += len(line)
            if header is not None:
                yield header, b"".join(lines).decode()


class FastaSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "fasta"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema):
        return _FastaReader(self.options["path"], int(self.options.get("span", 64 << 20)))


class _FastqReader(_FastaReader):
    """Records of four lines; a span begins at a line with @ whose third line begins with +."""

    def read(self, part: _Span) -> Iterator[tuple]:
        if not part.path:
            return
        with _open(part.path) as f:
            at, lines = part.begin, []
            if at:
                f.seek(at - 1)
                at += len(f.readline()) - 1
                for _ in range(8):
                    line = f.readline()
                    lines.append(line)
                    if len(lines) >= 3 and lines[-3].startswith(b"@") and lines[-1].startswith(b"+"):
                        at += sum(map(len, lines[:-3]))
                        lines = lines[-3:]
                        break
                    if not line:
                        return
            while True:
                while len(lines) < 4:
                    line = f.readline()
                    if not line:
                        return
                    lines.append(line)
                if at >= part.end:
                    return
                yield lines[0][1:].strip().decode(), lines[1].strip().decode(), lines[3].strip().decode()
                at += sum(map(len, lines))
                lines = []


class FastqSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "fastq"

    def schema(self) -> str:
        return SCHEMA + ", quality string"

    def reader(self, schema):
        return _FastqReader(self.options["path"], int(self.options.get("span", 64 << 20)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(FastaSource)
    spark.dataSource.register(FastqSource)


def read_fasta(spark: SparkSession, path: str, span: int = 64 << 20) -> DataFrame:
    """Local or mounted files, by bytes."""
    register(spark)
    return spark.read.format("fasta").option("path", path).option("span", span).load()


def read_fasta_any(spark: SparkSession, path: str) -> DataFrame:
    """Any store and codec that Spark reads, in splits where the codec has them (none, bzip2): a record begins with `>` at a line's start, so headers may hold any other `>`."""
    raw = spark.read.option("lineSep", "\n>").text(path)
    # the first record of a file has its own `>`; what stands before it is none
    named = raw.select(F.regexp_replace("value", "^\\s*>", "").alias("value")).where("length(trim(value)) > 0")
    lines = F.split("value", "\r?\n")
    return named.select(F.trim(lines[0]).alias("header"), F.array_join(F.transform(F.slice(lines, F.lit(2), F.size(lines)), lambda x: F.trim(x)), "").alias("s"))


def write_fasta(df: DataFrame, path: str, header: str = "header", s: str = "s", width: int = 60, compression: str | None = None) -> None:
    """Wrapped records in text files, one a partition."""
    wrapped = F.regexp_replace(F.col(s), f"(.{{1,{width}}})", "$1\n")
    text = F.rtrim(F.concat(F.lit(">"), F.regexp_replace(F.col(header).cast("string"), "[\r\n]+", " "), F.lit("\n"), wrapped))
    out = df.select(text.alias("value")).write.mode("overwrite")
    (out.option("compression", compression) if compression else out).text(path)


def write_fastq(df: DataFrame, path: str, header: str = "header", s: str = "s", quality: str = "I") -> None:
    text = F.concat(F.lit("@"), F.col(header).cast("string"), F.lit("\n"), F.col(s), F.lit("\n+\n"), F.expr(f"repeat('{quality}', length({s}))"))
    df.select(text.alias("value")).write.mode("overwrite").text(path)
