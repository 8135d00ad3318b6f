"""Inversion of a packed transform."""

import random

from blockbwt.operators import fmindex, packedsort, packedwalk
from blockbwt.operators.collection import DNA, StringCollection
from blockbwt.plans import catalogue
from blockbwt.plans.planner import Budget
from blockbwt.storage import materialise


def test_walks(spark):
    rnd = random.Random(9)
    rows = [(i * 11 - 70, "".join(rnd.choice("ACGT"[: rnd.choice([1, 2, 4])]) for _ in range(rnd.choice([0, 1, 5, 64, 90])))) for i in range(150)]
    coll = StringCollection(spark.createDataFrame(rows + [(5_000, "A" * 40), (5_001, "A" * 40)], "sid long, s string"), DNA)
    want = sorted(tuple(x) for x in coll.df.collect())
    for block in (37, 65536):
        pieces = materialise(packedsort.bwt_packed_pieces(coll, Budget(sort_rows=900), block), "bwt")
        back = packedwalk.invert_pieces(pieces, DNA, coll.longest(), 40)
        assert sorted(tuple(x) for x in back.collect()) == want


def test_a_larger_transform_is_left_to_joins(spark, monkeypatch):
    monkeypatch.setattr(packedwalk, "PLACES", 10)
    monkeypatch.setattr(fmindex, "invert", lambda bwt: bwt.where("sym is null").select("sid"))
    assert catalogue.QUERIES["invert_reads"](spark, "/root/testdata/sf0.001").count() == 3662


def test_inversion_of_reads_joins_no_places(spark, monkeypatch):
    """Before, pairs of places were joined for each doubling of the distance."""
    monkeypatch.setattr(fmindex, "invert", lambda *_: 1 / 0)
    assert catalogue.QUERIES["invert_reads"](spark, "/root/testdata/sf0.001").count() == 3662
