from rankfeed.sources import gradients as G
from rankfeed.streaming.days import daily_gradients
from tests.conftest import SF


def test_stream_of_days_equals_table(spark):
    schema = spark.read.parquet(f"{SF}/events.parquet").schema
    events = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(SF)
    query = daily_gradients(events).writeStream.format("memory").queryName("days").outputMode("complete").trigger(availableNow=True).start()
    query.awaitTermination(90)
    names = ["step", "worker", "i", "j", "v"]
    got = sorted(map(tuple, spark.table("days").select(names).collect()))
    assert got and got == sorted(map(tuple, G.daily(spark, SF).select(names).collect()))
