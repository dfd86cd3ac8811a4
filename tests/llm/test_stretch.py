"""Several copies of one item in one stretch of text."""


def test_worse_copy_before_a_better_one_is_reported(spark):
    from wavesum.llm.decontaminate import contaminated

    item = [f"word{chr(97 + i)}" for i in range(20)]
    worse = ["other", *item[1:10], "more", *item[11:]]
    docs = [(1, " ".join(["lead", "in", *worse, *item, "end"])), (2, " ".join([*item, *worse]))]
    table = spark.createDataFrame(docs, "doc_id bigint, text string")
    bench = spark.createDataFrame([(7, " ".join(item))], "item_id bigint, text string")
    got = sorted((r.doc_id, r.item_id) for r in contaminated(table, bench).collect())
    assert got == [(1, 7), (1, 7), (2, 7), (2, 7)]
