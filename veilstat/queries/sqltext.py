"""Pieces of DuckDB SQL that several checks share."""

KEY = "concat_ws('.', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(l_shipdate AS DATE))"


def coin(seed: str, purpose: str, *ids: str) -> str:
    """The md5 coin; ids are SQL expressions."""
    parts = ", ".join([f"'{seed}'", f"'{purpose}'", *[f"CAST({i} AS VARCHAR)" for i in ids]])
    return f"(('0x' || substr(md5(concat_ws('|', {parts})), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"


def hash_bits(seed: str, bits: int, *ids: str) -> str:
    parts = ", ".join([f"'{seed}'", *[f"length(CAST({i} AS VARCHAR)) || ':' || CAST({i} AS VARCHAR)" for i in ids]])
    return f"(('0x' || substr(md5(concat_ws('|', {parts})), 1, 8))::BIGINT % {1 << bits})"


def tidy(x: str) -> str:
    return f"(round({x}, 6) + 0.0)"


def h(n: str = "n") -> str:
    """Shannon entropy of counts."""
    return f"(ln(sum({n})) - sum(CASE WHEN {n} > 0 THEN {n} * ln({n}) ELSE 0 END) / sum({n}))"


def p2(n: str = "n") -> str:
    return f"(sum({n} * {n}) / (sum({n}) * sum({n})))"


def counts(table: str, *cols: str, where: str = "") -> str:
    c = ", ".join(cols)
    return f"SELECT {c}, CAST(count(*) AS DOUBLE) AS n FROM {table} {where} GROUP BY {c}"
