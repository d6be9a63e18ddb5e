"""The 20 patterns of a triad, in one table, and the column expressions that name a triad's pattern."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Pattern -> (family, nest links, regions common to three, to two only, to one only).
PATTERN_TABLE: dict[int, tuple[str, int, int, int, int]] = {
    1: ("CCC", 3, 1, 1, 1),
    2: ("TCC", 2, 1, 0, 2),
    3: ("TCC", 2, 1, 1, 2),
    4: ("TCC", 2, 1, 2, 0),
    5: ("TCC", 2, 1, 2, 1),
    6: ("TTC", 1, 1, 1, 2),
    7: ("TTC", 1, 1, 2, 1),
    8: ("TTC", 1, 1, 2, 2),
    9: ("TTT", 0, 1, 0, 3),
    10: ("TTT", 0, 1, 1, 3),
    11: ("TTT", 0, 1, 2, 2),
    12: ("TTT", 0, 1, 2, 3),
    13: ("TTT", 0, 1, 3, 0),
    14: ("TTT", 0, 1, 3, 1),
    15: ("TTT", 0, 1, 3, 2),
    16: ("TTT", 0, 1, 3, 3),
    17: ("TTT", 0, 0, 3, 0),
    18: ("TTT", 0, 0, 3, 1),
    19: ("TTT", 0, 0, 3, 2),
    20: ("TTT", 0, 0, 3, 3),
}
FAMILIES = ("CCC", "TCC", "TTC", "TTT")
CORE = tuple(p for p, s in PATTERN_TABLE.items() if s[0] == "TTT" and s[2])
CORELESS = tuple(p for p, s in PATTERN_TABLE.items() if s[0] == "TTT" and not s[2])


def members_of(family: str) -> tuple[int, ...]:
    return tuple(p for p, s in PATTERN_TABLE.items() if s[0] == family)


def pattern_rows(spark: SparkSession) -> DataFrame:
    """The 20 patterns as a table (pattern, family, nests, core, pairs, solos)."""
    return spark.createDataFrame([(p, *s) for p, s in PATTERN_TABLE.items()], "pattern int, family string, nests int, core int, pairs int, solos int")


def regions(wij: Column, wik: Column, wjk: Column, g: Column, ni: Column, nj: Column, nk: Column) -> dict[str, Column]:
    """Sizes of the seven regions of three sets: alone (i, j, k), in two only (ij, jk, ik), in all three."""
    return {
        "only_i": ni - wij - wik + g,
        "only_j": nj - wij - wjk + g,
        "only_k": nk - wik - wjk + g,
        "only_ij": wij - g,
        "only_jk": wjk - g,
        "only_ik": wik - g,
        "all_ijk": g,
    }


def _some(c: Column) -> Column:
    return (c > 0).cast("int")


def signature(wij: Column, wik: Column, wjk: Column, g: Column, ni: Column, nj: Column, nk: Column) -> Column:
    """nest links, core, pairs and solos packed into 7 bits: 2, 1, 2 and 2 of them."""
    r = regions(wij, wik, wjk, g, ni, nj, nk)
    nests = (wij == F.least(ni, nj)).cast("int") + (wik == F.least(ni, nk)).cast("int") + (wjk == F.least(nj, nk)).cast("int")
    pairs = _some(r["only_ij"]) + _some(r["only_jk"]) + _some(r["only_ik"])
    solos = _some(r["only_i"]) + _some(r["only_j"]) + _some(r["only_k"])
    return nests * 32 + _some(g) * 16 + pairs * 4 + solos


#: Pattern by signature; a constant array, so that typing a triad is one look-up.
_BY_SIGNATURE = [next((p for p, (_, n, c, d, s) in PATTERN_TABLE.items() if n * 32 + c * 16 + d * 4 + s == k), None) for k in range(128)]


def pattern_of(wij: Column, wik: Column, wjk: Column, g: Column, ni: Column, nj: Column, nk: Column) -> Column:
    """The pattern of a triad from overlaps and sizes."""
    table = F.array(*[F.lit(p).cast("int") for p in _BY_SIGNATURE])
    return F.element_at(table, signature(wij, wik, wjk, g, ni, nj, nk) + 1)


def pattern_of_sets(a: Column, b: Column, c: Column) -> Column:
    """The pattern of three literal sets (arrays without repeats); null unless they are distinct and meet pairwise."""
    ab, ac, bc = F.array_intersect(a, b), F.array_intersect(a, c), F.array_intersect(b, c)
    n = lambda x: F.size(x)
    meet = (n(ab) > 0) & (n(ac) > 0) & (n(bc) > 0)
    return F.when(meet, pattern_of(n(ab), n(ac), n(bc), n(F.array_intersect(ab, c)), n(a), n(b), n(c)))


def family_of(pattern: Column) -> Column:
    out = F.lit(None).cast("string")
    for family in FAMILIES:
        out = F.when(pattern.isin(*members_of(family)), family).otherwise(out)
    return out


def register_sql(spark: SparkSession) -> None:
    """hyper_pattern(a, b, c) for SQL: an expression function, so it stays inside generated code."""
    text = "NULL"
    for p, (_, nests, core, pairs, solos) in PATTERN_TABLE.items():
        text = f"CASE WHEN key = {nests * 1000 + core * 100 + pairs * 10 + solos} THEN {p} ELSE {text} END"
    body = f"""
      SELECT {text} FROM (SELECT
        1000 * (int(wij = least(ni, nj)) + int(wik = least(ni, nk)) + int(wjk = least(nj, nk))) + 100 * int(g > 0)
        + 10 * (int(wij > g) + int(wik > g) + int(wjk > g))
        + int(ni - wij - wik + g > 0) + int(nj - wij - wjk + g > 0) + int(nk - wik - wjk + g > 0) AS key
      FROM (SELECT size(a) ni, size(b) nj, size(c) nk, size(array_intersect(a, b)) wij, size(array_intersect(a, c)) wik,
                   size(array_intersect(b, c)) wjk, size(array_intersect(array_intersect(a, b), c)) g))
    """
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION hyper_pattern(a ARRAY<BIGINT>, b ARRAY<BIGINT>, c ARRAY<BIGINT>) RETURNS INT RETURN ({body})")
