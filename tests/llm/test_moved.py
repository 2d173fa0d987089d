from spangrid.llm import minhash


def _moved(plan) -> int:
    """Rows that the exchanges of a plan that has run have written."""
    if plan.nodeName() == "AdaptiveSparkPlan":
        return _moved(plan.executedPlan())
    if "QueryStage" in plan.nodeName():
        return _moved(plan.plan())
    own = plan.metrics().get("shuffleRecordsWritten")
    children = plan.children()
    return (own.get().value() if own.isDefined() else 0) + sum(_moved(children.apply(i)) for i in range(children.size()))


def test_keep_one_moves_only_what_may_go(spark):
    """Where the ids of dropped copies are too many to be shared, documents that stay are not moved to meet them."""
    rows = [(i, " ".join(f"w{j}" for j in range(i, i + 30))) for i in range(0, 60_000, 40)]
    docs = spark.createDataFrame([*rows, *((i + 1, t) for i, t in rows[:100])], "doc_id long, text string")
    was = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        out = minhash.keep_one(docs, 5)
        assert sorted(r["doc_id"] for r in out.collect()) == [i for i, _ in rows]
        assert 200 <= _moved(out._jdf.queryExecution().executedPlan()) < 500  # of 1600, and the 100 ids
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", was)
