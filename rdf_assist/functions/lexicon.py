"""The lexicon: what else a predicate may be called."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# Own words for the predicates of the given tables.
WORDS = {
    "supplier": "vendor seller provider suppliedBy", "customer": "buyer client orderedBy purchaser", "nation": "country state", "region": "continent area",
    "marketSegment": "industry sector", "part": "product item component", "totalPrice": "cost amount", "orderDate": "purchaseDate orderedOn", "shipDate": "deliveryDate shippedOn",
    "brand": "make manufacturer", "accountBalance": "balance credit", "line": "sentence text", "title": "heading headline",
}


def lexicon(spark: SparkSession) -> DataFrame:
    """(term, verbalization)."""
    return spark.createDataFrame([(t, v) for t, words in WORDS.items() for v in words.split()], "term string, verbalization string")


def verbalize(terms: DataFrame, lex: DataFrame) -> DataFrame:
    """(term, form): each term as it is and as every word the lexicon lists with it, whichever side it stands on."""
    both = lex.select("term", F.col("verbalization").alias("form")).unionByName(lex.select(F.col("verbalization").alias("term"), F.col("term").alias("form")))
    return terms.select("term", F.col("term").alias("form")).unionByName(terms.join(both, "term").select("term", "form")).distinct()
