"""The sieve before the exact stage keeps every wanted row."""

from lmrel.llm.jaccard import sifted


def test_sieve_keeps_wanted_rows(spark):
    docs = spark.createDataFrame([(i, f"t{i}") for i in range(-500, 5000)] + [(None, "none")], "node long, text string")
    wanted = docs.where("node % 7 = 0").select("node")
    got = sifted(docs, wanted)
    assert got.columns == ["node", "text"]
    assert got.join(wanted, "node").count() == wanted.count()
    assert got.count() < wanted.count() + 50
    assert sifted(docs, wanted.limit(0)).count() == 0
