"""polyprov: how-provenance for relational queries, as Spark DataFrame plans."""

__version__ = "0.1.0"
