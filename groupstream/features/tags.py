"""Tag vectors: learned from co-occurrence with Word2Vec, or hashed, which needs no training and is repeatable."""

from __future__ import annotations

from pyspark.ml.feature import Word2Vec
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..functions.linalg import vec_mean
from ..sources.tables import Tables

DIM = 4


def item_tags(tables: Tables) -> DataFrame:
    """(v, tags): the words of an item's name, its brand and its type, each once, in order."""
    tags = F.concat(F.split("p_name", " "), F.array("p_brand", "p_type"))
    return tables.part.select(F.col("p_partkey").alias("v"), F.sort_array(F.array_distinct(F.filter(tags, lambda t: t != ""))).alias("tags"))


def hashed_tag_vectors(tagged: DataFrame, d: int = DIM) -> DataFrame:
    """(v, vec): the mean of the tags' hashed vectors, with components in [-1, 1). Items are dealt before tags are hashed, since
    a table of items has few files and hashing takes longer than moving them."""
    tags = tagged.repartition("v").select("v", F.explode("tags").alias("tag"))
    vector = F.array(*[2 * uniform(f"tag{i}", "tag") - 1 for i in range(d)])
    return tags.withColumn("vec", vector).groupBy("v").agg(vec_mean(F.col("vec"), d).alias("vec"))


def tag_vectors(tagged: DataFrame, size: int = DIM, seed: int = 1, min_count: int = 1) -> DataFrame:
    """(v, vec): Word2Vec over the tag lists; its transform already averages an item's tags."""
    model = Word2Vec(vectorSize=size, seed=seed, minCount=min_count, inputCol="tags", outputCol="w2v", numPartitions=1, maxIter=1).fit(tagged)
    return model.transform(tagged).select("v", vector_to_array("w2v").alias("vec"))


def group_tag_vectors(interactions: DataFrame, items: DataFrame, d: int = DIM) -> DataFrame:
    """(g, vec): the mean of the tag vectors of the items a group touched."""
    return interactions.select("g", "v").join(items, "v").groupBy("g").agg(vec_mean(F.col("vec"), d).alias("vec"))
