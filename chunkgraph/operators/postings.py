"""An inverted index as chunked sets: a token's documents are an ordered set, queries are set operations."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import sets


def token_id(token):
    """A 48-bit id of a token."""
    return F.conv(F.substring(F.md5(token), 1, 12), 16, 10).cast("long")


@dataclass(frozen=True)
class PostingIndex:
    chunks: DataFrame
    b: int = 16

    @staticmethod
    def tokens(docs: DataFrame, text: str = "text") -> DataFrame:
        """(owner, elem): token ids and doc_id of lower-cased runs of a-z; null texts have none."""
        listed = docs.select("doc_id", F.explode(F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0))).alias("token"))
        return listed.select(token_id(F.col("token")).alias("owner"), F.col("doc_id").alias("elem")).distinct()

    @staticmethod
    def build(docs: DataFrame, b: int = 16) -> "PostingIndex":
        return PostingIndex(sets.build(PostingIndex.tokens(docs), b), b)

    def add_docs(self, docs: DataFrame) -> "PostingIndex":
        return PostingIndex(sets.union(self.chunks, self.tokens(docs), self.b), self.b)

    def remove_docs(self, docs: DataFrame) -> "PostingIndex":
        return PostingIndex(sets.difference(self.chunks, self.tokens(docs), self.b), self.b)

    def of(self, token: str) -> DataFrame:
        """One token's set, under owner 0, so that sets of different tokens can be combined."""
        return self.chunks.where(F.col("owner") == token_id(F.lit(token))).withColumn("owner", F.lit(0).cast("long"))

    def and_(self, a: str, c: str) -> DataFrame:
        return self._docs(sets.intersect(self.of(a), self.of(c)))

    def or_(self, a: str, c: str) -> DataFrame:
        return self._docs(sets.union(self.of(a), sets.entries(self.of(c)), self.b))

    def minus(self, a: str, c: str) -> DataFrame:
        return self._docs(sets.difference(self.of(a), sets.entries(self.of(c)), self.b))

    @staticmethod
    def _docs(chunks: DataFrame) -> DataFrame:
        return sets.entries(chunks).select(F.col("elem").alias("doc_id"))
