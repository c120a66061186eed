from pyspark.sql import functions as F

from pairmatch.streaming import online as L
from tests.oracle import SF


def test_streamed_windows_equal_batch(spark, tmp_path):
    e = spark.read.parquet(f"{SF}/events.parquet")
    e.orderBy("ts").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = L.read_events(spark, str(tmp_path / "in"), e.schema)
    q = L.windowed(stream, "6 hours").writeStream.format("memory").queryName("wins").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination(120)
    want = L.windowed(e.withColumn("ts", F.col("ts").cast("timestamp")), "6 hours")
    assert spark.table("wins").exceptAll(want).count() == 0 and spark.table("wins").count() == want.count()
