"""Counter-based coins: every random choice is a function of a seed, a purpose and ids.

A recomputed task draws the same coin again, which retries need and privacy too: a second
draw for the same user would be a second report. Public seeds (pairing, salts, budgets) and
private seeds (noise) are separate arguments. A known seed makes tests repeatable; it is no
source of private randomness for real users.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 4294967296.0


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def uniform(seed: str, purpose: str, *ids, kind: str = "md5") -> Column:
    """A number in [0, 1) with 32 bits. ``md5`` can be repeated in other engines, ``xxhash64`` is faster."""
    parts = [F.lit(seed), F.lit(purpose), *[_col(i).cast("string") for i in ids]]
    if kind == "xxhash64":
        return F.shiftrightunsigned(F.xxhash64(*parts), 32).cast("double") / F.lit(SPAN)
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("double") / F.lit(SPAN)


def draw(seed: str, purpose: str, *ids) -> float:
    """The ``md5`` coin on the driver."""
    text = "|".join([seed, purpose, *map(str, ids)])
    return int(hashlib.md5(text.encode()).hexdigest()[:8], 16) / SPAN


def hash_bits(seed: str, bits: int, *ids) -> Column:
    """A public hash to [0, 2^bits) of length-prefixed parts, so that no two inputs share an encoding."""
    parts = [F.concat(F.length(_col(i).cast("string")).cast("string"), F.lit(":"), _col(i).cast("string")) for i in ids]
    word = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(seed), *parts)), 1, 8), 16, 10).cast("long")
    return (word % F.lit(1 << bits)).cast("int")


def symbol(column: Column | str) -> Column:
    """Any column as text, null as a symbol of its own, NaN as one symbol and -0.0 as 0.0."""
    c = F.col(column) if isinstance(column, str) else column
    return F.coalesce(c.cast("string"), F.lit("∅"))
