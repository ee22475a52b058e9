"""Reproducible draws: a retried task or another engine must see the same number, so they are hashes and never random generators."""

from __future__ import annotations

SPARK, DUCKDB = "spark", "duckdb"


def uniform_sql(text: str, seed: int, dialect: str = SPARK) -> str:
    """A number in [0, 1) from the first 32 bits of the MD5 of ``seed:text``."""
    digest = f"substring(md5(concat('{seed}:', CAST({text} AS {'STRING' if dialect == SPARK else 'VARCHAR'}))), 1, 8)"
    whole = f"CAST(conv({digest}, 16, 10) AS DOUBLE)" if dialect == SPARK else f"CAST(CAST(concat('0x', {digest}) AS BIGINT) AS DOUBLE)"
    return f"({whole} / 4294967296e0)"


def draw_sql(seed: int, scope: str = "transaction", dialect: str = SPARK) -> str:
    """One draw for the whole transaction ``t``, or with scope ``anchor`` one for each (t, i), which spreads the total more evenly."""
    if scope == "transaction":
        return uniform_sql("t", seed, dialect)
    kind = "STRING" if dialect == SPARK else "VARCHAR"
    return uniform_sql(f"concat(CAST(t AS {kind}), '/', CAST(i AS {kind}))", seed, dialect)
