"""Operator 6: Merkle fingerprints of documents (DataFrame functions only).

A text is cut at line ends and after words whose hash WORD_SHARE divides; words
are what white space ends. Longer runs than LONG characters (scripts without
spaces, encoded data) are cut after characters whose hash with the two before
them RUN_SHARE divides. So cuts follow the content in any script and case, and an
edit changes only the leaves it touches; a leaf of more than MOST words (or
characters of a run) is cut at every MOST of them from its begin on. Leaves are
hashed; a section is a run of leaves that ends at a leaf whose hash 16 divides
(about one in 16); a section's node hashes its leaves, and a text of more than
MOST_NODES sections has a further level, made of sections the same way, up to
LEVELS; the root hashes the uppermost ones.

The fingerprint has a bounded size: the root, the uppermost nodes, and the SKETCH
smallest leaves. Equal texts have equal roots; where two differ, the nodes that
the other lacks locate the edit (`locate`), and `sections` says where those are in
the text. Likeness is the Jaccard coefficient of the two sets of leaves: exact up
to SKETCH different leaves, and beyond that estimated from the smallest ones of
both (a standard error of 0.044 at most).

The next document and how much of it an edit takes are found on (doc_id, hash,
length) alone: ranges of doc_id, neighbours within a range, and the one first
row of each range for the range before it. Texts move once, by their key.

Defined results: a null text is an empty one; an empty text has one empty leaf;
documents are ordered by descending doc_id, null last, then by the text's hash;
rows that repeat doc_id and text stand at one place of that order and give as many
equal rows; an empty table gives no row; a lone document is its own next one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

DIGITS = 16
SKETCH, MOST_NODES, LEVELS = 128, 256, 4
WORD_SHARE, RUN_SHARE, LONG, MOST = 5, 16, 24, 64


def leaves(text: Column) -> Column:
    """The 64-bit hash of each leaf in order."""
    return _cut(text, lambda p, e: F.transform(e, lambda end, i: _leaf(p, e, end, i)))


def _cut(text: Column, use) -> Column:
    """use(pieces, how many of them there are up to the end of each leaf)."""
    words = F.split(text, r"(?<=\s)(?=\S)")
    marked = F.transform(words, lambda w: F.when(F.length(w) > LONG, _run(w)).otherwise(F.array(_piece(w, F.xxhash64(w), WORD_SHARE))))
    return _once(F.flatten(marked), lambda p: _once(_ends(p), lambda e: use(p, e)))


def _once(value: Column, use) -> Column:
    """use(value), with value computed once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _piece(piece: Column, h: Column, share: int) -> Column:
    return F.struct(piece.alias("p"), ((F.pmod(h, F.lit(share)) == 0) | F.contains(piece, F.lit("\n"))).alias("cut"))


def _run(word: Column) -> Column:
    """The characters of a long run, each cut or not by itself and the two before it."""
    near = lambda c, x, i: F.xxhash64(F.get(c, i - 2), F.get(c, i - 1), x)
    return _once(F.split(word, ""), lambda c: F.transform(c, lambda x, i: _piece(x, near(c, x, i), RUN_SHARE)))


def _ends(pieces: Column) -> Column:
    """How many pieces there are up to the end of each leaf."""
    n = F.size(pieces)
    cuts = F.filter(F.transform(pieces, lambda p, i: F.when(p["cut"] | (i == n - 1), i + 1)), lambda x: x.isNotNull())
    return _once(cuts, lambda c: F.flatten(F.transform(c, lambda end, i: _bounded(F.coalesce(F.get(c, i - 1), F.lit(0)), end))))


def _bounded(begin: Column, end: Column) -> Column:
    return F.when(end - begin <= MOST, F.array(end)).otherwise(F.concat(F.sequence(begin + MOST, end - 1, F.lit(MOST)), F.array(end)))


def _leaf(pieces: Column, ends: Column, end: Column, i: Column) -> Column:
    begin = F.coalesce(F.get(ends, i - 1), F.lit(0))
    return F.xxhash64(F.transform(F.slice(pieces, begin + 1, end - begin), lambda p: p["p"]))


def _hex(x: Column) -> Column:
    return F.lpad(F.lower(F.hex(x)), DIGITS, "0")


def _up(nodes: Column) -> Column:
    """The nodes above: runs that end at a node 16 divides, each the hash of its run, which it begins with for a bound on what is in it."""
    n = F.size(nodes)
    cuts = F.filter(F.transform(nodes, lambda x, i: F.when((F.pmod(x, F.lit(16)) == 0) | (i == n - 1), i + 1)), lambda x: x.isNotNull())
    run = lambda c, end, i: F.slice(nodes, F.coalesce(F.get(c, i - 1), F.lit(0)) + 1, end - F.coalesce(F.get(c, i - 1), F.lit(0)))
    return _once(cuts, lambda c: F.transform(c, lambda end, i: F.xxhash64(run(c, end, i))))


def nodes(leaf: Column) -> Column:
    """The uppermost nodes under the root: sections, or for long texts what is above them."""
    top = _once(leaf, _up)
    for _ in range(LEVELS - 1):
        top = _once(top, lambda x: F.when(F.size(x) > MOST_NODES, _up(x)).otherwise(x))
    return top


def sketch(leaf: Column) -> Column:
    return F.slice(F.array_sort(F.array_distinct(leaf)), 1, SKETCH)


def fingerprint(leaf: Column) -> Column:
    """root:node.node...:leaf.leaf..., the leaves being the smallest ones."""
    said = lambda x: F.array_join(F.transform(x, _hex), ".")
    return _once(said(nodes(leaf)), lambda top: F.concat(F.sha2(F.concat(top, F.lit("/"), F.size(leaf).cast("string")).cast("binary"), 256), F.lit(":"), top, F.lit(":"), said(sketch(leaf))))


def sketch_of(fingerprint: Column) -> Column:
    """The smallest leaves that a fingerprint holds, as numbers."""
    return F.transform(F.split(F.substring_index(fingerprint, ":", -1), "[.]"), lambda x: F.conv(x, 16, -10).cast("long"))


def likeness(a: Column, b: Column) -> Column:
    """Of two sketches, 0 to 1."""
    both = lambda u: F.size(F.array_intersect(F.array_intersect(u, a), b)) / F.size(u).cast("double")
    return _once(F.slice(F.array_sort(F.array_union(a, b)), 1, SKETCH), both)


def locate(a: Column, b: Column) -> Column:
    """Nodes of fingerprint a that b lacks: where a was edited. Equal roots give none without looking."""
    parts = lambda x: F.split(F.element_at(F.split(x, ":"), 2), "[.]")
    same = F.substring_index(a, ":", 1) == F.substring_index(b, ":", 1)
    return F.when(same, F.array().cast("array<string>")).otherwise(F.array_except(parts(a), parts(b)))


def sections(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, section, node, start, n_chars): the sections of each text and where they stand, from character 0."""
    body = F.coalesce(F.col(text), F.lit(""))
    cut = _cut(body, lambda p, e: F.transform(e, lambda end, i: F.struct(_leaf(p, e, end, i).alias("h"), F.aggregate(F.slice(p, F.coalesce(F.get(e, i - 1), F.lit(0)) + 1, end - F.coalesce(F.get(e, i - 1), F.lit(0))), F.lit(0), lambda a, x: a + F.length(x["p"])).alias("n"))))
    size = lambda run: F.aggregate(run, F.lit(0), lambda a, x: a + x["n"])
    told = lambda r: F.struct(_hex(F.xxhash64(F.transform(r, lambda x: x["h"]))).alias("node"), size(r).cast("long").alias("n"))

    def runs(leaf: Column) -> Column:
        last = F.size(leaf) - 1
        ends = F.filter(F.transform(leaf, lambda x, i: F.when((F.pmod(x["h"], F.lit(16)) == 0) | (i == last), i + 1)), lambda x: x.isNotNull())
        run = lambda c, end, i: F.slice(leaf, F.coalesce(F.get(c, i - 1), F.lit(0)) + 1, end - F.coalesce(F.get(c, i - 1), F.lit(0)))
        return _once(ends, lambda c: F.transform(c, lambda end, i: _once(run(c, end, i), told)))

    found = df.select(F.col(doc_id).alias("doc_id"), _once(cut, runs).alias("s"))
    placed = found.select("doc_id", "s", F.posexplode("s").alias("section", "own"))
    start = F.aggregate(F.slice("s", F.lit(1), F.col("section")), F.lit(0).cast("long"), lambda a, x: a + x["n"])
    return placed.select("doc_id", "section", "own.node", start.alias("start"), F.col("own.n").alias("n_chars"))


def fingerprints(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fingerprint), a row for each row of df."""
    return df.select(F.col(doc_id).alias("doc_id"), fingerprint(leaves(F.coalesce(F.col(text), F.lit("")))).alias("fingerprint"))


def neighbours(keys: DataFrame) -> DataFrame:
    """Distinct (doc_id, h, n, copies) -> each with the row that follows in descending order, and after the last the first.

    Ranges are written with their rows, since a range's bounds come from a
    sample and must not be drawn twice; their number is the shuffle's.
    """
    order = [F.col("doc_id").desc_nulls_last(), F.col("h").desc()]
    ranged = common.materialise(keys.repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "ranges")
    row = F.struct("doc_id", "h", "n")
    # the first of a part by the order: null doc_ids come last of all
    first = ranged.groupBy("part").agg(F.max(F.struct(F.col("doc_id").isNotNull().alias("k"), "doc_id", "h", "n")).alias("first"))
    by_part = Window.orderBy("part")  # a row for each range
    heads = first.select("part", F.coalesce(F.lead("first").over(by_part), F.first("first").over(by_part)).alias("head"))
    inner = ranged.withColumn("next", F.lead(row).over(Window.partitionBy("part").orderBy(*order)))
    joined = inner.join(F.broadcast(heads), "part")
    head = F.struct("head.doc_id", "head.h", "head.n")
    return joined.select("doc_id", "h", "n", "copies", F.coalesce("next", head).alias("next"))


def edits(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_chars, edited, fingerprint, edited_fingerprint, near_edited, near_next) of each document and of its edit by the next one, a row for each row of df."""
    body = F.coalesce(F.col(text), F.lit(""))
    given_id = F.col(doc_id).cast("long")
    keyed = df.select(*_key(given_id), F.xxhash64(body).alias("h"), body.alias("text"))
    keys = df.select(given_id.alias("doc_id"), F.xxhash64(body).alias("h"), F.length(body).cast("long").alias("n")).groupBy("doc_id", "h", "n").agg(F.count(F.lit(1)).alias("copies"))
    near = common.materialise(neighbours(keys), "neighbours")
    # what a document owes to the one before it
    owes = near.select(*_key(F.col("next.doc_id")), F.col("next.h").alias("h"), *_key(F.col("doc_id"), "to_"), F.col("h").alias("to_h"), F.floor(F.col("n") / 3).alias("k"), "copies")
    once = Window.partitionBy("d", "z", "h").orderBy(F.lit(0))
    own = keyed.withColumn("_before", F.lag(F.lit(1)).over(once)).where("_before is null").drop("_before")
    given = own.join(owes, ["d", "z", "h"]).select(F.col("to_d").alias("d"), F.col("to_z").alias("z"), F.col("to_h").alias("h"), F.expr("substring(text, 1, cast(k as int))").alias("given"), sketch(leaves(F.col("text"))).alias("next_leaf"), "copies")
    both = own.join(given, ["d", "z", "h"]).select(F.when(~F.col("z"), F.col("d")).alias("doc_id"), "copies", "text", "given", "next_leaf", leaves(F.col("text")).alias("leaf"), F.length("text").cast("long").alias("n_chars"))
    edited = F.concat(F.expr("substring(text, 1, cast(n_chars - floor(n_chars / 3) as int))"), F.col("given"))
    done = both.withColumn("edited", edited).withColumn("edited_leaf", leaves(F.col("edited")))
    own_leaf = sketch(F.col("leaf"))
    told = done.select("doc_id", "copies", "n_chars", "edited", fingerprint(F.col("leaf")).alias("fingerprint"), fingerprint(F.col("edited_leaf")).alias("edited_fingerprint"), likeness(own_leaf, sketch(F.col("edited_leaf"))).alias("near_edited"), likeness(own_leaf, F.col("next_leaf")).alias("near_next"))
    return told.select("*", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies")))).drop("copies", "col")


def _key(doc_id: Column, before: str = "") -> list[Column]:
    """doc_id as columns without nulls, so that joins and windows share one partitioning."""
    return [F.coalesce(doc_id, F.lit(0)).alias(f"{before}d"), doc_id.isNull().alias(f"{before}z")]


def op6_merkle(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = edits(common.table(spark, sf_dir, "documents"))
    return done.select("doc_id", "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), "fingerprint", "edited_fingerprint", "near_edited", "near_next")
