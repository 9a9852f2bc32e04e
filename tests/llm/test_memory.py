"""What the operators hold at once on the driver."""

from pyspark.sql import functions as F

from rankfeed.llm import near_dedup
from rankfeed.llm.runtime import bits_for


def test_bit_tables_are_as_large_as_the_tokens_of_their_level(spark):
    often = spark.range(0, 6000).select(F.xxhash64("id").alias("token"), F.when(F.col("id") < 10, 200).otherwise(2).alias("sets"))
    tables = near_dedup.frequency_bits(often)
    assert [size for _, size in tables] == [bits_for(6000), *[bits_for(10)] * 3]
    assert sum(bits.nbytes for bits, _ in tables) < 2 * bits_for(6000) // 8
    for token, sets in ((r.token, r.sets) for r in often.collect()):
        for level, (bits, size) in enumerate(tables):
            if sets >= 2 * 4**level:
                assert bits[token % size >> 3] >> (token % size & 7) & 1
    assert near_dedup.frequency_bits(often.where("sets < 0")) == []
