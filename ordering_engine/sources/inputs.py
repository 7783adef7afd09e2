"""The ten input instances, as keys derived from the ids of a given table's rows.

Only the key is derived; placement, payload and row counts stay those of the table. The formulas are
arithmetic on the dense uid, so the same SQL text serves Spark and DuckDB.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import DUCK, SPARK, Dialect
from ..storage import staged

V = 1 << 31
NAMES = ("uniform", "gaussian", "bucket_sorted", "group", "zero", "det_dupl", "rand_dupl", "staggered", "mirrored", "all_to_one")


def key_sql(name: str, n: int, p: int, d: Dialect, seed: int = 42, g: int = 4) -> str:
    """SQL of the key from the columns uid, pe, pos (0-based on the PE) and m (the PE's load)."""
    r, q, bits = d.hash("uid", seed), V // p, p.bit_length() - 1
    if name == "uniform":
        return r
    if name == "gaussian":
        return d.div(" + ".join(d.hash("uid", seed + i) for i in range(4)), 4)
    if name == "bucket_sorted":
        return f"(pe * {q} + {r} % {q})"
    if name == "group":
        g = min(g, p)
        return f"((({d.div('pe', g)} * {g} + {p // 2} + least({d.div(f'pos * {g}', 'm')}, {g - 1})) % {p}) * {q} + {r} % {q})"
    if name == "zero":
        return "cast(0 AS bigint)"
    if name == "det_dupl":
        level = " + ".join(f"(CASE WHEN pe >= {p - p // 2**t} THEN 1 ELSE 0 END)" for t in range(1, bits + 1)) or "0"
        return f"cast({max(n, 1).bit_length() - 1} - ({level}) AS bigint)"
    if name == "rand_dupl":
        run = d.div("uid", f"(1 + {d.hash(d.div('uid', 64), seed)} % 16)")
        return f"({d.hash(f'({run} + {d.div("uid", 64)} * 64)', seed + 1)} % 32)"
    if name == "staggered":
        b = f"(CASE WHEN pe < {p // 2} THEN 2 * pe + 1 ELSE 2 * (pe - {p // 2}) END)" if p > 1 else "0"
        return f"({b} * {q} + {r} % {q})"
    if name == "mirrored":
        m = " + ".join(f"({d.div('pe', 1 << i)} % 2) * {1 << (bits - 1 - i)}" for i in range(bits)) or "0"
        return f"(({m}) * {q} + {r} % {q})"
    if name == "all_to_one":
        w = ((1 << 32) - p) // p
        return f"(CASE WHEN pos < m - 1 THEN {p} + ({p} - pe) * {w} + {r} % {w} ELSE {p} - pe END)"
    raise KeyError(name)


def _placed(uid_table: str, n: int, p: int, d: Dialect) -> str:
    pe = d.div(f"cast(uid AS bigint) * {p}", max(n, 1))
    start, after = d.div(f"(pe * {n} + {p - 1})", p), d.div(f"((pe + 1) * {n} + {p - 1})", p)
    return f"SELECT uid, pe, uid - {start} AS pos, {after} - {start} AS m FROM (SELECT uid, {pe} AS pe FROM ({uid_table}) AS t) AS t"


def instance_sql(name: str, uid_table: str, n: int, p: int, d: Dialect, seed: int = 42) -> str:
    """A query of pe, key, uid over a query that gives dense uids."""
    return f"SELECT cast(pe AS int) AS pe, cast({key_sql(name, n, p, d, seed)} AS bigint) AS key, cast(uid AS bigint) AS uid FROM ({_placed(uid_table, n, p, d)}) AS placed"


def make(name: str, base: DataFrame, p: int, seed: int = 42, n: int | None = None) -> DataFrame:
    """Held elements (pe, key, uid) of an instance over the first n rows by uid of a table with dense uids."""
    base = base.select("uid") if n is None else base.select("uid").where(F.col("uid") < n)
    base.createOrReplaceTempView("__instance_base")
    size = n if n is not None else base.count()
    return staged(base.sparkSession.sql(instance_sql(name, "SELECT uid FROM __instance_base", size, p, SPARK, seed)), f"instance-{name}")


def make_many(cases: list[tuple[str, int]], base: DataFrame, p: int, seed: int = 42) -> DataFrame:
    """Instances (name, n) side by side: that of case c on the PEs c * p to c * p + p - 1."""
    base.select("uid").createOrReplaceTempView("__instance_base")
    parts = [f"SELECT cast(pe + {c * p} AS int) AS pe, key, uid FROM ({instance_sql(name, f'SELECT uid FROM __instance_base WHERE uid < {n}', n, p, SPARK, seed)}) AS made" for c, (name, n) in enumerate(cases)]
    return staged(base.sparkSession.sql(" UNION ALL ".join(parts)), "instances")


def oracle(name: str, table: str, id_column: str, n: int, p: int, seed: int = 42) -> str:
    """The same in DuckDB, with uids from a row number over the id."""
    return instance_sql(name, f"SELECT row_number() OVER (ORDER BY {id_column}) - 1 AS uid FROM {table}", n, p, DUCK, seed)
