import json

from semrank.sources.ranker_log import read_logs
from semrank.streaming import topk as streams


def test_ranker_logs(spark, tmp_path):
    good = [{"call_id": f"c{i}", "query": "q", "ids": [1, 2], "ranked": [2, 1], "seconds": 0.5} for i in range(3)]
    (tmp_path / "a.jsonl").write_text("\n".join([*map(json.dumps, good), '{"call_id": "cut', "[1]", ""]))
    (tmp_path / "b.jsonl").write_text(json.dumps({"call_id": "partial"}))
    (tmp_path / "other.txt").write_text("x")
    rows = {r["call_id"]: r for r in read_logs(spark, f"file://{tmp_path}").collect()}
    assert set(rows) == {"c0", "c1", "c2", "partial"} and rows["c0"]["ranked"] == [2, 1] and rows["partial"]["ids"] is None
    (tmp_path / "none").mkdir()
    assert read_logs(spark, f"file://{tmp_path}/none").count() == 0


def test_late_rows_are_counted(spark, tmp_path):
    first = spark.sql("SELECT timestamp '2024-01-02 00:00:00' AS ts, 1L AS id")
    late = spark.sql("SELECT timestamp '2024-01-01 00:00:00' AS ts, 2L AS id")
    first.coalesce(1).write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(first.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    counts = stream.withWatermark("ts", "1 hour").groupBy("ts").count()
    run = lambda: counts.writeStream.format("noop").outputMode("update").option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
    q = run()
    q.awaitTermination()
    assert streams.late_rows(q) == 0
    late.coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    q = run()
    q.awaitTermination()
    assert streams.late_rows(q) == 1
