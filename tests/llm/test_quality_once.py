from lowrank_spark.llm import quality_rules as qr


def test_lines_are_hashed_once(spark, monkeypatch):
    """The line counts that the rules are drawn from are a table, so the texts are not split again for each use of them."""
    plans, real = [], qr.boilerplate

    def watched(freq, *more):
        plans.append(freq._jdf.queryExecution().optimizedPlan().toString())
        return real(freq, *more)

    monkeypatch.setattr(qr, "boilerplate", watched)
    docs = spark.createDataFrame([(n, f"shared line\nown line {'x' * n}", "h") for n in range(12)], "doc_id long, text string, source string")
    got = {r.doc_id: r.n_removed_words for r in qr.mark_boilerplate(docs).collect()}
    assert got == {n: 2 for n in range(12)}
    assert len(plans) == 1 and "Generate" not in plans[0]
