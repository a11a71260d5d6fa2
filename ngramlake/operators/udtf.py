"""Table functions and the SQL surface of the search."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ngramlake.functions import similarity
from ngramlake.functions.text import WORD, tokens
from ngramlake.operators import soft


def register(spark: SparkSession) -> None:
    """``text_windows(text, n)`` as a table function, beside the scalar SQL functions."""

    class TextWindows:
        def eval(self, text: str, n: int):
            import regex  # knows the classes that the tokenizer's pattern names

            t = regex.findall(WORD, (text or "").lower())
            for i in range(len(t) - n + 1):
                yield i, " ".join(t[i : i + n])

    spark.udtf.register("text_windows", F.udtf(TextWindows, returnType="pos: int, gram: string"))
    similarity.register_sql(spark)


def soft_search_view(spark: SparkSession, name: str, text: str, theta: float, near: DataFrame, find: soft.Finder, n: int = 20) -> DataFrame:
    """Answers one typed query as a temporary view: ranked patterns with hit counts."""
    q = spark.range(1).select(F.col("id").alias("query_id"), tokens(F.lit(text)).alias("tokens"))
    q = q.withColumn("m", F.size("tokens"))
    m = q.first()["m"]
    out = soft.top_patterns(soft.soft_search(q, theta, near, find, m), n).select("rank", F.replace("key", F.lit("\x01"), F.lit(" ")).alias("pattern"), "similarity", "hits")
    out.createOrReplaceTempView(name)
    return out
