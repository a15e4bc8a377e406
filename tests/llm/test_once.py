"""What is dear is made once."""

from coreset_spark.llm import line_dedup


def test_line_dedup_finds_fragments_once(spark):
    shared = "\n".join(f"line {i} " + "word " * 9 for i in range(9))
    docs = spark.createDataFrame([(i, f"own {i}\n{shared}\nend {i}") for i in range(3)], "doc_id long, text string")
    out = line_dedup.dedup(docs)
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "shiftrightunsigned" not in plan.replace(" ", "").lower() and ">>>" not in plan  # the rolling hash is behind the checkpoint
    assert [len(r["text"].split("\n")) for r in out.orderBy("doc_id").collect()] == [11, 2, 2]
