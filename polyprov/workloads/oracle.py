"""Small builders of DuckDB SQL for annotated results."""

from __future__ import annotations

TOKEN = {
    "region": "'r:' || r_regionkey", "nation": "'n:' || n_nationkey", "supplier": "'s:' || s_suppkey", "customer": "'c:' || c_custkey",
    "part": "'p:' || p_partkey", "orders": "'o:' || o_orderkey", "events": "'e:' || event_id", "documents": "'d:' || doc_id",
    "labels": "'lb:' || doc_id", "benchmark": "'b:' || item_id", "pages": "'pg:' || page_id", "embeddings": "'x:' || vec_id",
    "lineitem": "'l:' || l_orderkey || '.' || l_partkey || '.' || l_suppkey || '.' || l_linenumber", "conversations": "'v:' || conv_id || '.' || turn",
}


def token(table: str, alias: str | None = None) -> str:
    """Token of a table's row, its columns behind an alias."""
    if alias is None:
        return TOKEN[table]
    out = []
    for part in TOKEN[table].split(" || "):
        out.append(part if part.startswith("'") else f"{alias}.{part}")
    return " || ".join(out)


def times(*parts: str) -> str:
    return " || ' · ' || ".join(parts)


def plus(p: str, label: str = " + ") -> str:
    return f"string_agg({p}, '{label}' ORDER BY {p})"


def delta(p: str) -> str:
    return f"'δ(' || {plus(p)} || ')'"


def text(x: str) -> str:
    """A double as tensors show it."""
    return f"CAST(CAST({x} AS DECIMAL(18,4)) AS VARCHAR)"


def tensor(p: str, x: str) -> str:
    return f"({p}) || '⊗' || {x}"


def formal(p: str, x: str, monoid: str) -> str:
    empty = "1⊗0" if monoid == "count" else "0"
    return f"COALESCE({plus(tensor(p, x), f' +{monoid} ')}, '{empty}')"


def number(x: str) -> str:
    """A double result as the queries deliver it."""
    return f"CAST(CAST({x} AS DECIMAL(30,4)) AS DOUBLE)"


def whole(x: str) -> str:
    return f"CAST({x} AS BIGINT)"


def grouped(keys: list[tuple[str, str]], aggs: list[tuple[str, str, str, str]], source: str, prov: str, tail: str = "") -> str:
    """Grouped select: keys (sql, name), aggregates (name, value sql, term text, monoid)."""
    cols = [f"{k} AS {n}" for k, n in keys]
    cols += [f"{v} AS {n}" for n, v, _, _ in aggs] + [f"{formal(prov, t, m)} AS {n}_agg" for n, _, t, m in aggs]
    cols.append(f"{delta(prov)} AS prov" if keys else "'1' AS prov")
    group = f" GROUP BY {', '.join(str(i + 1) for i in range(len(keys)))}" if keys else ""
    return f"SELECT {', '.join(cols)} FROM {source}{group}{tail}"
