import os
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def test_contract(spark):
    import __spark_entry__ as e

    q, sql = e.queries(), e.oracle_sql()
    assert set(sql) <= set(q) and len(q) > 100 and len(sql) > 90
    row = e.entry(spark).collect()
    assert len(row) == 1 and row[0].violations == 0


def test_core_stands_alone(tmp_path):
    """Without the text operators everything else imports."""
    code = (
        "import sys\n"
        "class Gone:\n"
        "    def find_spec(self, name, path=None, target=None):\n"
        "        if name.startswith('setanon.llm') or name == 'corpus_pipeline':\n"
        "            raise ModuleNotFoundError(name)\n"
        "sys.meta_path.insert(0, Gone())\n"
        "import __spark_entry__ as e\n"
        "assert 'anonymize_suppress_k3' in e.queries() and not any(k.startswith('op') for k in e.queries() if k[2:3].isdigit())\n"
        "assert e.oracle_sql()\n"
    )
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True)


def test_plans(spark):
    """Pruned columns, no cross join, and few exchanges on the bucketed path."""
    from setanon.operators import lsh, threads
    from setanon.plans.pipeline import AnonOptions, anonymize
    from setanon.sources import tables

    d = "/root/testdata/sf0.001"
    text = lambda df: df._jdf.queryExecution().executedPlan().toString()
    scan = text(tables.market_baskets(spark, d))
    assert "l_extendedprice" not in scan and "o_totalprice" not in scan
    assert "Exchange" not in text(lsh.precluster(spark.createDataFrame([("1", "u", ["a"])], "record_id string, user_id string, items array<string>"), 3)).replace("ExistingRDD", "")
    recs = spark.createDataFrame([(str(i), "u", ["a", str(i % 3)]) for i in range(30)], "record_id string, user_id string, items array<string>")
    solved = anonymize(recs, 3, AnonOptions(p=2)).solved
    plan = text(solved)
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    log = tables.order_log(spark, d)
    plan = text(threads.similar_queries(log))
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
