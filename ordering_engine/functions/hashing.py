"""Arithmetic randomness: a function of (uid, seed), the same in Spark and DuckDB, so that reruns and retries agree."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 2147483647
#: Multiplier and shift of each round. Two rounds leave neighbours correlated, three don't.
ROUNDS = ((48271, 13), (69621, 16), (39373, 11))


class Dialect:
    """The few operators that Spark SQL and DuckDB spell differently."""

    def __init__(self, duck: bool):
        self.duck = duck

    def div(self, a, b) -> str:
        return f"(({a}) // ({b}))" if self.duck else f"(({a}) div ({b}))"

    def xor(self, a, b) -> str:
        return f"xor({a}, {b})" if self.duck else f"(({a}) ^ ({b}))"

    def shr(self, a, s) -> str:
        return f"(({a}) >> {s})" if self.duck else f"shiftright({a}, {s})"

    def hash(self, uid: str, seed: int) -> str:
        """[0, 2^31 - 1), three rounds."""
        x = f"(cast({uid} AS bigint) % {PRIME})"
        for a, s in ROUNDS:
            y = f"(({x} * {a} + {seed}) % {PRIME})"
            x = self.xor(y, self.shr(y, s))
        return f"({x} % {PRIME})"


SPARK, DUCK = Dialect(False), Dialect(True)


def uid_hash(uid: str, seed: int) -> Column:
    return F.expr(SPARK.hash(uid, seed))


def unit(uid: str, seed: int) -> Column:
    return uid_hash(uid, seed) / F.lit(float(PRIME))
