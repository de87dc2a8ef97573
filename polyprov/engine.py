"""The engine: register base relations, ask SQL or DataFrame queries, get provenance."""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from polyprov.errors import ProvenanceTooLarge, UnsupportedForProvenance
from polyprov.functions.algebra import ALGEBRAS, Algebra
from polyprov.operators.frame import AnnotatedFrame
from polyprov.options import Options
from polyprov.plans.annotate import Annotator
from polyprov.sources.tokens import GIVEN, TokenPolicy, assert_unique_tokens


@dataclass(frozen=True)
class ProvResult:
    """The annotated result, as a lazy DataFrame, and what it does not say."""

    df: DataFrame
    frame: AnnotatedFrame
    caveats: tuple[str, ...]
    rewrite_seconds: float


#: A Parquet writer looks at its size first after 100 rows, then after as many as the
#: rows so far let it expect.  Where a row may hold megabytes of text, some of them would
#: be held at once, several times over; so it looks after each row, and a page of wide
#: rows has one.  Readers of whole batches hold a row group's texts uncompressed, and grow
#: their buffers twofold; so row groups are smaller than usual (counted as compressed).
#: Lists of tokens are long and alike: zstd takes half the disk of Spark's usual codec.
WIDE_ROWS = {
    "parquet.page.size.check.estimate": "false", "parquet.page.size.row.check.min": "1", "parquet.page.size.row.check.max": "16",
    "parquet.block.size.row.check.min": "1", "parquet.block.size.row.check.max": "16", "parquet.block.size": str(32 << 20),
    "spark.sql.parquet.compression.codec": "zstd",
}

#: A Parquet writer copies a column's least and greatest text whenever one passes them, and
#: holds both for each row group until its file ends, to leave out long ones there.
#: Columns of annotations are written without.
NO_STATISTICS = "parquet.column.statistics.enabled"


class Engine:
    def __init__(self, spark: SparkSession, options: Options = Options()):
        self.spark, self.options = spark, options
        for k, v in WIDE_ROWS.items():
            self._default(k, v)
        self.policies: dict[str, TokenPolicy] = {}

    def _default(self, key: str, value: str) -> None:
        if self.spark.conf.get(key, None) is None:
            self.spark.conf.set(key, value)

    def register(self, name: str, df: DataFrame, policy: TokenPolicy | None = None, check: bool = False) -> None:
        """A base relation as temporary view, with its token policy."""
        policy = policy or GIVEN.get(name) or TokenPolicy(name, kind="content_hash")
        if check:
            assert_unique_tokens(df, policy)
        df.createOrReplaceTempView(name)
        self.policies[name.lower()] = policy

    def register_folder(self, sf_dir: str, names: list[str] | None = None, qualified: bool = False) -> Engine:
        """The given Parquet tables of a folder."""
        for name in names or list(GIVEN):
            policy = GIVEN[name]
            if qualified:
                policy = policy.qualified(sf_dir.rstrip("/").rsplit("/", 1)[-1], "main", name)
            self.register(name, self.spark.read.parquet(f"{sf_dir}/{name}.parquet"), policy)
        return self

    def policy(self, name: str) -> TokenPolicy:
        found = self.policies.get(name.lower())
        if found is None:
            raise UnsupportedForProvenance(f"{name} is not registered")
        return found

    def plain(self, query: str | DataFrame) -> DataFrame:
        return self.spark.sql(query) if isinstance(query, str) else query

    def frame(self, query: str | DataFrame, algebra: Algebra | None = None, **options) -> tuple[AnnotatedFrame, list]:
        return Annotator(self.policy, replace(self.options, **options), algebra).run(self.plain(query))

    def provenance(self, query: str | DataFrame, algebra: Algebra | None = None, **options) -> ProvResult:
        """Rewrite a query; nothing runs before an action on the result's DataFrame."""
        began = time.perf_counter()
        af, output = self.frame(query, algebra, **options)
        df = af.delivered(output)
        given = {a.name() for a in output or () if a.exprId().id() not in af.aggs}
        for f in df.schema:
            if f.name not in given and isinstance(f.dataType, StringType):
                self._default(f"{NO_STATISTICS}#{f.name}", "false")
        return ProvResult(df, af, af.caveats, time.perf_counter() - began)

    def text_size(self, query: str | DataFrame) -> int:
        """Characters of the longest annotation that the text form would have."""
        return self.provenance(query, ALGEBRAS["length"]).df.agg(F.max("prov")).first()[0] or 0

    def within_budget(self, query: str | DataFrame, or_circuit: bool = True, **options):
        """Text annotations if none passes ``max_text_bytes``; else the circuit
        (annotated result, circuit), or ProvenanceTooLarge."""
        from polyprov.functions.circuit import circuit

        size = self.text_size(query)
        if size <= replace(self.options, **options).max_text_bytes:
            return self.provenance(query, **options)
        if or_circuit:
            return circuit(self, query)
        raise ProvenanceTooLarge(f"an annotation of {size} characters")

    def provenance_of(self, query: str | DataFrame, rows: Column | str) -> DataFrame:
        """The query as a circuit, expanded to text for chosen result rows only."""
        from polyprov.functions.circuit import circuit

        df, c = circuit(self, query)
        chosen = df.where(rows)
        texts = c.expand(chosen.select(F.col("prov").alias("gate")))
        return chosen.join(texts, chosen["prov"] == texts["gate"]).drop("gate", "prov").withColumnRenamed("x", "prov")

    def rewrite(self, query: str | DataFrame, **options) -> DataFrame:
        return self.provenance(query, **options).df

    def explain(self, query: str | DataFrame, **options) -> str:
        return self.rewrite(query, **options)._jdf.queryExecution().explainString(self.spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
