"""How large a sketch must be, and how often it errs.

N distinct keys, Z tables of H counters each; f is the rate at which a stored key's count is wrong.
"""

from __future__ import annotations

import math
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: ln 2 squared, negated: log(0.6185...), the best achievable error per byte of a one-byte counter.
BEST_RATE = math.exp(-math.log(2) ** 2)
HALF = 0.5


def is_prime(n: int) -> bool:
    """Deterministic Miller-Rabin for 64-bit numbers."""
    if n < 2:
        return False
    small = (2, 3, 5, 7, 11, 13, 17, 19, 23, 29, 31, 37)
    for p in small:
        if n % p == 0:
            return n == p
    d, r = n - 1, 0
    while d % 2 == 0:
        d, r = d // 2, r + 1
    for a in small:
        x = pow(a, d, n)
        if x in (1, n - 1):
            continue
        for _ in range(r - 1):
            x = x * x % n
            if x == n - 1:
                break
        else:
            return False
    return True


def prime_table_sizes(size: float, tables: int) -> list[int]:
    """The `tables` largest distinct primes that are at most `size`, descending."""
    out, n = [], int(size)
    while len(out) < tables:
        if n < 2:
            raise ValueError(f"there are no {tables} primes up to {size}")
        if is_prime(n):
            out.append(n)
        n -= 1
    return out


def collision_rate(n: float, h: float, exact: bool = False) -> float:
    """Chance that a key shares its counter with another one in a table."""
    return 1 - (1 - 1 / h) ** n if exact else -math.expm1(-n / h)


def expected_fpr(n: float, h, z: int | None = None) -> float:
    """Chance that a key shares all of its counters: tables of one size, or of each of the given sizes."""
    sizes = [h] * (z or 1) if isinstance(h, int | float) else list(h)
    return math.prod(collision_rate(n, x) for x in sizes)


def optimal_tables(memory: float, n: float) -> int:
    """Tables that err least in `memory` counters: ln 2 * M / N, rounded to the better side."""
    best = math.log(2) * memory / n
    options = {max(1, math.floor(best)), max(1, math.ceil(best))}
    return min(options, key=lambda z: (expected_fpr(n, memory / z, z), z))


@dataclass(frozen=True)
class Size:
    tables: float
    table_size: float
    memory: float


def size_for_fpr(n: float, f: float, tables: int | None = None, exact: bool = False) -> Size:
    """Tables, counters per table and counters in all for N keys at error rate f.

    The closed form takes the best real number of tables; `exact` inverts the rate for a whole number of them.
    """
    if not 0 < f < 1 or n <= 0:
        raise ValueError("0 < f < 1 and N > 0")
    if exact or tables:
        z = tables or max(1, round(math.log(f, HALF)))
        h = -n / math.log(1 - f ** (1 / z))
        return Size(z, h, h * z)
    z = math.log(f, HALF)
    h = math.log(f, BEST_RATE) * n / z
    return Size(z, h, h * z)


def distinct_from_load(occupied: int, h: int) -> float:
    """Distinct keys that fill `occupied` of h counters (linear counting on one table)."""
    return float("inf") if occupied >= h else -h * math.log1p(-occupied / h)


def overcount_bound(total: float, h: float, z: int, factor: float = math.e) -> dict[str, float]:
    """Expected excess of one table, and the chance that all tables exceed `factor` times it (Markov's bound)."""
    return {"expected_excess": total / h, "excess": factor * total / h, "chance": factor**-z}


def partitioned_memory(n: float, f: float, parts: int) -> dict[str, float]:
    """Counters in all, and in one of `parts` equal parts of the key space."""
    memory = size_for_fpr(n, f).memory
    return {"memory": memory, "part_memory": memory / parts}


def information_floor(n: float, k: int) -> float:
    """Least bits per key for any exact set of n of the 4^k words."""
    total = 4.0**k
    ln = math.lgamma(total + 1) - math.lgamma(n + 1) - math.lgamma(total - n + 1) if total < 1e15 else n * (math.log(total) - math.log(n) + 1) - 0.5 * math.log(2 * math.pi * n)
    return ln / math.log(2) / n


def sizing_grid(spark: SparkSession, n: float, memories: list[int], tables: list[int]) -> DataFrame:
    """Error rate for each memory and number of tables."""
    m = spark.createDataFrame([(int(x),) for x in memories], "memory long")
    z = spark.createDataFrame([(int(x),) for x in tables], "tables int")
    fpr = F.pow(1 - F.exp(-F.lit(float(n)) * F.col("tables") / F.col("memory")), F.col("tables"))
    return m.join(z, F.col("memory") > F.col("tables")).select("memory", "tables", fpr.alias("fpr"))


def table_bytes(df: DataFrame) -> int:
    """The bytes that the engine expects a table to have."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def parts_for(df: DataFrame, bytes_each: int = 64 << 20, least: int = 16, most: int = 100_000) -> int:
    """Into how many parts to deal a table's words: by the bytes that the engine expects it to have, if it knows."""
    size = table_bytes(df)
    if size >= 2**56:  # the engine's stand-in for a size that it can't tell
        return max(least, 4 * int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return max(least, min(most, -(-size // bytes_each)))


def as_rows(spark: SparkSession, sizes: dict[str, Size]) -> DataFrame:
    return spark.createDataFrame([(k, *map(float, asdict(v).values())) for k, v in sizes.items()], "name string, tables double, table_size double, memory double")
