"""The given tables, and collections made of them, with the same in SQL for checks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blockbwt.operators.collection import DNA, StringCollection

_LETTERS = "abcdefghijklmnopqrstuvwxyz"
_BASES = ("ACGT" * 7)[:26]


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """df over all cores where its scan has few splits, such as one file of one row group; a scan of many stays as it is. What follows makes a hundred rows of each string, so the texts' own exchange is small beside it."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(2 * cores) if df._jdf.rdd().getNumPartitions() < 4 * cores else df


def dna(text):
    return F.translate(F.regexp_replace(F.lower(text), "[^a-z]", ""), _LETTERS, _BASES)


def reads(spark: SparkSession, sf_dir: str, length: int = 100, stride: int | None = None, join: int = 1) -> StringCollection:
    """Windows of the documents' letters as bases; `join` neighbours of a document make one read, incomplete groups go."""
    stride = stride or length
    whole = spread(load(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", dna(F.col("text")).alias("t"))
    size = length * join
    if length % stride or join > 1 and stride != length:
        number = F.when(F.length("t") >= length, F.floor((F.length("t") - length) / stride) + 1).otherwise(0)
        number = F.floor(number / 4) * 4 if join > 1 else number
        each = whole.withColumn("n", number / F.lit(join)).where("n >= 1").select("doc_id", "t", F.explode(F.sequence(F.lit(0), (F.col("n") - 1).cast("int"))).alias("i"))
        return StringCollection(each.select(_read_id(F.col("i")).alias("sid"), F.expr(f"substring(t, i * {stride * join} + 1, {size})").alias("s")), DNA, size)
    # a text is cut into pieces of `stride` once; a read is a few neighbours of them
    pieces = F.regexp_extract_all("t", F.lit(f".{{{stride}}}"), F.lit(0))
    cut = whole.select("doc_id", pieces.alias("p"))
    if join == 1 and length == stride:
        return _numbered(cut, F.col("p"), size)
    of = join if join > 1 else length // stride
    number = F.floor(F.size("p") / 4) * 4 / join if join > 1 else F.size("p") - of + 1
    first = (lambda i: i * join + 1) if join > 1 else (lambda i: i + 1)
    some = F.when(number >= 1, F.transform(F.sequence(F.lit(0), (number - 1).cast("int")), lambda i: F.array_join(F.slice("p", first(i), F.lit(of)), "")))
    return _numbered(cut, some, size)


def _numbered(cut: DataFrame, pieces, size: int) -> StringCollection:
    """A row for each piece. The outer form, since the plain one puts a filter on the array's size below it, which would cut every text three times."""
    each = cut.select("doc_id", F.posexplode_outer(pieces).alias("i", "s")).where("s is not null")
    return StringCollection(each.select(_read_id(F.col("i")).alias("sid"), "s"), DNA, size)


#: Reads of one document have so many ids.
READ_IDS = 100_000


def _read_id(i):
    """The i-th read's id; a document of more reads than it has ids for is an error, since they would be those of the next."""
    too_many = F.raise_error(F.concat(F.lit("a document has more reads than ids: "), F.col("doc_id").cast("string"))).cast("bigint")
    return F.when(i >= READ_IDS, too_many).otherwise(F.col("doc_id") * READ_IDS + i)


def reads_sql(length: int = 100, stride: int | None = None, join: int = 1) -> str:
    stride = stride or length
    n = f"CASE WHEN length(t) >= {length} THEN (length(t) - {length}) // {stride} + 1 ELSE 0 END"
    n = f"({n}) // 4 * 4 // {join}" if join > 1 else n
    return f"""SELECT CAST(doc_id * 100000 + i AS BIGINT) AS sid, substr(t, CAST(i * {stride * join} + 1 AS BIGINT), {length * join}) AS s FROM (
        SELECT doc_id, t, unnest(range(0, CAST({n} AS BIGINT))) AS i FROM (
        SELECT doc_id, translate(regexp_replace(lower(text), '[^a-z]', '', 'g'), '{_LETTERS}', '{_BASES}') AS t FROM documents))"""


def by_column(spark: SparkSession, sf_dir: str, table: str, sid: str, s: str, alphabet=None) -> StringCollection:
    return StringCollection.of(load(spark, sf_dir, table), sid, s, alphabet)


def event_codes(spark: SparkSession, sf_dir: str) -> StringCollection:
    """A string for each user: the event types in order of time as A to E."""
    e = load(spark, sf_dir, "events")
    code = F.element_at(F.create_map(*[F.lit(x) for k, v in zip(("click", "error", "purchase", "signup", "view"), "ABCDE") for x in (k, v)]), F.col("event_type"))
    said = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", code.alias("c")))), lambda x: x["c"]), "")
    return StringCollection(e.groupBy(F.col("user_id").alias("sid")).agg(said.alias("s")), tuple("ABCDE"))


EVENTS_SQL = "SELECT user_id AS sid, string_agg(CASE event_type WHEN 'click' THEN 'A' WHEN 'error' THEN 'B' WHEN 'purchase' THEN 'C' WHEN 'signup' THEN 'D' ELSE 'E' END, '' ORDER BY ts, event_id) AS s FROM events GROUP BY user_id"


def order_status(spark: SparkSession, sf_dir: str) -> StringCollection:
    o = load(spark, sf_dir, "orders")
    said = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("o_orderdate", "o_orderkey", "o_orderstatus"))), lambda x: x["o_orderstatus"]), "")
    return StringCollection(o.groupBy(F.col("o_custkey").alias("sid")).agg(said.alias("s")))


STATUS_SQL = "SELECT o_custkey AS sid, string_agg(o_orderstatus, '' ORDER BY o_orderdate, o_orderkey) AS s FROM orders GROUP BY o_custkey"

_FLAGS = ("AF", "AO", "NF", "NO", "RF", "RO")


def line_flags(spark: SparkSession, sf_dir: str) -> StringCollection:
    rows = load(spark, sf_dir, "lineitem")
    pair = F.concat("l_returnflag", "l_linestatus")
    code = F.element_at(F.create_map(*[F.lit(x) for k, v in zip(_FLAGS, "ABCDEF") for x in (k, v)]), pair)
    said = F.array_sort(F.collect_list(F.struct("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", code.alias("c"))))
    return StringCollection(rows.groupBy(F.col("l_orderkey").alias("sid")).agg(F.array_join(F.transform(said, lambda x: x["c"]), "").alias("s")), tuple("ABCDEF"))


_CASE = " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in zip(_FLAGS, "ABCDEF"))
FLAGS_SQL = f"""SELECT l_orderkey AS sid, string_agg(c, '' ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, c) AS s
    FROM (SELECT *, CASE l_returnflag || l_linestatus {_CASE} END AS c FROM lineitem) GROUP BY l_orderkey"""


def embedding_signs(spark: SparkSession, sf_dir: str) -> StringCollection:
    e = load(spark, sf_dir, "embeddings")
    s = F.array_join(F.transform("embedding", lambda x: F.when(x >= 0, "1").otherwise("0")), "")
    return StringCollection(e.select(F.col("vec_id").alias("sid"), s.alias("s")), ("0", "1"))


SIGNS_SQL = "SELECT vec_id AS sid, array_to_string(list_transform(embedding, lambda x: CASE WHEN x >= 0 THEN '1' ELSE '0' END), '') AS s FROM embeddings"


def conversation_turns(spark: SparkSession, sf_dir: str) -> StringCollection:
    c = load(spark, sf_dir, "conversations")
    return StringCollection(c.select((F.col("conv_id") * 1000 + F.col("turn")).alias("sid"), F.col("text").alias("s")))


TURNS_SQL = "SELECT CAST(conv_id * 1000 + turn AS BIGINT) AS sid, text AS s FROM conversations"


def coverage_reads(spark: SparkSession, sf_dir: str) -> StringCollection:
    """Reads that overlap fourfold."""
    return reads(spark, sf_dir, 100, 25)


__all__ = [x for x in dir() if not x.startswith("_") and x != "Window"]
