"""Text reports: topics by labels or by keywords, then the miner on the reports' features."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def words(column: str):
    return F.filter(F.split(F.lower(column), "[^\\p{L}]+"), lambda w: F.length(w) > 2)


def topics_supervised(docs: DataFrame, labels: DataFrame, text: str = "text", label: str = "topic", buckets: int = 1 << 12) -> DataFrame:
    """doc_id and predicted topic (0/1) from labelled reports (doc_id, topic)."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF

    own = docs.select("doc_id", words(text).alias("words"))
    model = Pipeline(stages=[HashingTF(numFeatures=buckets, inputCol="words", outputCol="features", binary=True), LogisticRegression(labelCol=label, maxIter=10, regParam=0.01)]).fit(own.join(labels.select("doc_id", F.col(label).cast("double").alias(label)), "doc_id"))
    return model.transform(own).select("doc_id", F.col("prediction").cast("int").alias("topic"))


def topics_unsupervised(docs: DataFrame, k: int, text: str = "text", vocabulary: int = 500) -> DataFrame:
    """doc_id and its strongest of k topics."""
    from pyspark.ml.clustering import LDA
    from pyspark.ml.feature import CountVectorizer
    from pyspark.ml.functions import vector_to_array

    own = docs.select("doc_id", words(text).alias("words"))
    counted = CountVectorizer(inputCol="words", outputCol="features", vocabSize=vocabulary).fit(own).transform(own)
    found = LDA(k=k, maxIter=5, seed=1).fit(counted).transform(counted).select("doc_id", vector_to_array("topicDistribution").alias("share"))
    return found.select("doc_id", (F.array_position("share", F.array_max("share")) - 1).cast("int").alias("topic"))


def keyword_topics(docs: DataFrame, by: str, top: int, text: str = "text") -> DataFrame:
    """The words that occur in most texts of each group."""
    counted = docs.select(by, F.explode(F.array_distinct(F.filter(F.split(F.lower(text), "[^a-z]+"), lambda w: F.length(w) > 2))).alias("word")).groupBy(by, "word").agg(F.count("*").alias("n"))
    return counted.withColumn("rank", F.row_number().over(W.partitionBy(by).orderBy(F.desc("n"), "word"))).where(F.col("rank") <= top)
