"""Sources, sinks, table functions and plan facts."""

from corpus_audit.functions import udtf
from corpus_audit.plans import costs
from corpus_audit.plans.registry import QUERIES
from corpus_audit.sources import io


def test_round_trips(spark, sf, tmp_path):
    docs = io.documents(spark, sf)
    io.write_corpus(docs, f"{tmp_path}/parquet")
    assert spark.read.parquet(f"{tmp_path}/parquet").count() == docs.count()
    io.write_json(docs, f"{tmp_path}/json")
    back = io.read_jsonl(spark, f"{tmp_path}/json")
    assert back.schema == io.CORE_SCHEMA and back.exceptAll(docs).count() == 0
    docs.select("doc_id", "corpus", "subset", "text", "url", "created", "lang").write.option("header", True).option("escape", '"').csv(f"{tmp_path}/csv")
    assert io.read_csv(spark, f"{tmp_path}/csv").count() == docs.count()


def test_whole_files(spark, tmp_path):
    (tmp_path / "a.txt").write_text("two\nlines")
    assert io.read_text(spark, f"{tmp_path}/a.txt", "files").first()["text"] == "two\nlines"


def test_table_function(spark, sf):
    udtf.register(spark, sf)
    assert [r["gram"] for r in spark.sql("SELECT gram FROM explode_ngrams('a b c', 2)").collect()] == ["a b", "b c"]
    assert spark.sql("SELECT count(*) FROM documents").first()[0] == 200


def test_partition_pruning_and_columns(spark, sf, tmp_path):
    io.write_corpus(io.documents(spark, sf), f"{tmp_path}/c")
    plan = spark.read.parquet(f"{tmp_path}/c").filter("corpus = 'src1'").select("doc_id")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(corpus" in plan and "ReadSchema: struct<doc_id:bigint>" in plan


def test_plans_have_no_nested_loop_where_none_is_needed(spark, sf):
    for name in ("text_duplicates", "top_bigrams", "hashed_cells", "text_overlap_pairs", "summary_stats"):
        assert costs.plan_facts(QUERIES[name](spark, sf))["CartesianProduct"] == 0


def test_costs():
    assert costs.dollars(3600) == 9.46 and round(costs.dollars(168_711), 1) == 443.3
