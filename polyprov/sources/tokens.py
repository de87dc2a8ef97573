"""Tokens: one identifier per base row, built by a narrow deterministic expression."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from polyprov.errors import NonUniqueTokens

KINDS = ("key", "content_hash", "row_index", "uuid_persisted")


@dataclass(frozen=True)
class TokenPolicy:
    """How the rows of a table are identified.

    *key* joins the key columns behind a prefix; ``strict`` adds a hash of the other
    columns, for keys that are not quite unique.  *content_hash* needs no key.
    *row_index* uses the file and the row's place in it (Parquet only).
    *uuid_persisted* expects a column with identifiers written once beforehand.
    ``source`` (database#schema#table) qualifies tokens for federated queries.
    """

    prefix: str
    key: tuple[str, ...] = ()
    kind: str = "key"
    strict: bool = False
    source: str | None = None

    def __post_init__(self):
        if self.kind not in KINDS:
            raise ValueError(f"unknown token kind {self.kind}")

    def qualified(self, database: str, schema: str, table: str) -> TokenPolicy:
        return replace(self, source=f"{database}#{schema}#{table}")

    def column(self, columns: Sequence[str]) -> Column:
        """The token as an expression over a table with these columns."""
        quoted = lambda c: F.col(f"`{c}`")
        if self.kind == "key":
            body = F.concat_ws(".", *[F.coalesce(quoted(c).cast("string"), F.lit("null")) for c in self.key])
            rest = [c for c in columns if c not in self.key]
            if self.strict and rest:
                body = F.concat(body, F.lit("~"), F.hex(content_hash(rest)))
        elif self.kind == "content_hash":
            body = F.hex(content_hash(columns))
        elif self.kind == "row_index":
            body = F.concat(F.col("_metadata.file_name"), F.lit("#"), F.col("_metadata.row_index").cast("string"))
        else:
            body = quoted(self.key[0]).cast("string")
        token = F.concat(F.lit(f"{self.prefix}:"), body) if self.prefix else body
        return F.concat(F.lit(f"{self.source}:"), token) if self.source else token


def content_hash(columns: Sequence[str]) -> Column:
    """64-bit hash in which a null differs from every value and place (Spark's
    hash functions skip nulls)."""
    marks = F.concat(*[F.when(F.col(f"`{c}`").isNull(), "0").otherwise("1") for c in columns])
    return F.xxhash64(marks, *[F.col(f"`{c}`") for c in columns])


def persist_uuids(df: DataFrame, path: str, name: str = "row_token") -> DataFrame:
    """Write ``df`` once with a random identifier per row, and read that back.

    Random identifiers are safe against retries only once they are stored.
    """
    df.withColumn(name, F.expr("uuid()")).write.parquet(path)
    return df.sparkSession.read.parquet(path)


def assert_unique_tokens(df: DataFrame, policy: TokenPolicy) -> None:
    """Raise if two rows share a token (one aggregation, combined before its shuffle)."""
    twice = df.groupBy(policy.column(df.columns).alias("token")).agg(F.count("*").alias("n")).where("n > 1").limit(1).collect()
    if twice:
        raise NonUniqueTokens(f"{twice[0].token} names {twice[0].n} rows")


#: Token policies of the given tables.
GIVEN = {
    "region": TokenPolicy("r", ("r_regionkey",)),
    "nation": TokenPolicy("n", ("n_nationkey",)),
    "supplier": TokenPolicy("s", ("s_suppkey",)),
    "customer": TokenPolicy("c", ("c_custkey",)),
    "part": TokenPolicy("p", ("p_partkey",)),
    "orders": TokenPolicy("o", ("o_orderkey",)),
    "lineitem": TokenPolicy("l", ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")),
    "events": TokenPolicy("e", ("event_id",)),
    "documents": TokenPolicy("d", ("doc_id",)),
    "labels": TokenPolicy("lb", ("doc_id",)),
    "benchmark": TokenPolicy("b", ("item_id",)),
    "pages": TokenPolicy("pg", ("page_id",)),
    "embeddings": TokenPolicy("x", ("vec_id",)),
    "conversations": TokenPolicy("v", ("conv_id", "turn")),
}
