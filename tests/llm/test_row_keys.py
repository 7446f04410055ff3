from farpoint.llm.decontam import drop_contaminated
from farpoint.llm.simhash import drop_near_duplicates


def test_null_and_repeated_ids_lose_only_the_rows_judged(spark):
    item = "one two three four five six seven eight nine ten eleven twelve thirteen"
    said = [f"{x} " * 30 for x in ("alpha beta gamma", "delta epsilon zeta", "eta theta iota", "kappa lambda mu", "nu xi omicron")]
    rows = [(None, said[0]), (None, said[1]), (None, said[2]), (1, said[2]), (7, said[3]), (7, said[4]), (7, said[4]), (None, item), (7, item), (8, None), (None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    left = drop_near_duplicates(spark, docs)
    assert sorted(map(str, (tuple(r) for r in left.collect()))) == sorted(map(str, [rows[0], rows[1], rows[3], rows[4], rows[5], rows[8], rows[9]]))
    emptied = spark.createDataFrame([(5, said[0]), (5, ""), (9, "")], "doc_id long, text string")
    assert sorted(map(str, (tuple(r) for r in drop_near_duplicates(spark, emptied).collect()))) == sorted(map(str, [(5, said[0]), (9, "")]))
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    clean = drop_contaminated(spark, docs, bench)
    assert sorted(map(str, (tuple(r) for r in clean.collect()))) == sorted(map(str, (r for r in rows if r[1] != item)))
