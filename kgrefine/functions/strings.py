"""String kernels that Spark has no function for, as Arrow functions, and name signals as column expressions."""

from __future__ import annotations

from difflib import SequenceMatcher
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


@lru_cache(maxsize=100_000)
def seq_ratio_py(a: str, b: str) -> float:
    """Twice the characters in longest matching runs over both lengths."""
    return SequenceMatcher(None, a, b, autojunk=False).ratio()


@lru_cache(maxsize=100_000)
def jaro_winkler_py(a: str, b: str, weight: float = 0.1, from_: float = 0.7) -> float:
    """Jaro similarity, raised by up to four common first characters where it is over ``from_``."""
    if a == b:
        return 1.0
    if not a or not b:
        return 0.0
    reach = max(0, max(len(a), len(b)) // 2 - 1)
    used, mine = [False] * len(b), []
    for i, c in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not used[j] and b[j] == c:
                used[j] = True
                mine.append(c)
                break
    m = len(mine)
    if not m:
        return 0.0
    theirs = [c for c, u in zip(b, used, strict=True) if u]
    moved = sum(x != y for x, y in zip(mine, theirs, strict=True)) // 2
    jaro = (m / len(a) + m / len(b) + (m - moved) / m) / 3
    if jaro <= from_:
        return jaro
    prefix = 0
    while prefix < min(4, len(a), len(b)) and a[prefix] == b[prefix]:
        prefix += 1
    return jaro + prefix * weight * (1 - jaro)


_VOWELS = frozenset("AEIOUY")
#: Fixed values of the phonetic code: a group of letters and its primary and secondary sound, tried before single letters.
_GROUPS = (
    ("SCHW", "X", "X", 4), ("TSCH", "X", "X", 4), ("SCH", "X", "SK", 3), ("TCH", "X", "X", 3), ("CIA", "X", "X", 2), ("TIO", "X", "X", 2), ("TIA", "X", "X", 2), ("CZ", "S", "X", 2), ("ZH", "J", "J", 2), ("SH", "X", "X", 2),
    ("PH", "F", "F", 2), ("TH", "0", "T", 2), ("WH", "A", "A", 2), ("DG", "J", "J", 2), ("CK", "K", "K", 2), ("CQ", "K", "K", 2), ("GN", "N", "KN", 2), ("MB", "M", "M", 2), ("QU", "K", "K", 2), ("TZ", "TS", "TS", 2), ("KH", "K", "K", 2),
)
_SINGLE = {"B": "P", "D": "T", "F": "F", "K": "K", "L": "L", "M": "M", "N": "N", "P": "P", "Q": "K", "R": "R", "V": "F", "X": "KS", "Z": "S", "Ç": "S", "Ñ": "N"}


@lru_cache(maxsize=100_000)
def double_metaphone_py(word: str, length: int = 4) -> tuple[str, str]:
    """Primary and secondary sound codes of one word, at most ``length`` letters each."""
    s = "".join(c for c in word.upper() if c.isalpha())
    one, two, i = "", "", 0
    if s[:2] in ("GN", "KN", "PN", "WR", "PS"):
        i = 1
    elif s[:1] == "X":
        one, two, i = "S", "S", 1

    def at(k: int, n: int = 1) -> str:
        return s[k : k + n] if k >= 0 else ""

    while i < len(s) and (len(one) < length or len(two) < length):
        c = s[i]
        if c in _VOWELS:
            if i == 0:
                one, two = one + "A", two + "A"
            i += 1
            continue
        group = next((g for g in _GROUPS if s.startswith(g[0], i)), None)
        if group and not (group[0] == "WH" and i > 0) and not (group[0] == "MB" and i + 2 < len(s)) and not (group[0] == "GN" and i == 0):
            one, two, i = one + group[1], two + group[2], i + group[3]
            continue
        if c == "C":
            if at(i + 1) == "H":
                p, q = ("K", "K") if i == 0 and at(i + 2) in ("R", "L", "O") and s[i : i + 4] != "CHOR" or at(i - 1) == "S" else ("X", "K")
                n = 2
            elif at(i + 1) in ("I", "E", "Y"):
                p, q, n = ("S", "S", 1) if at(i + 1) != "I" or at(i + 2) != "O" else ("X", "S", 1)
            else:
                p, q, n = "K", "K", 2 if at(i + 1) in ("C", "K", "G") and at(i + 2) not in ("I", "E") else 1
        elif c == "G":
            if at(i + 1) == "H":
                silent = i > 0 and at(i - 1) not in _VOWELS or i > 0 and at(i + 2) not in _VOWELS
                p, q, n = ("", "", 2) if silent and at(i - 1) not in ("U",) else ("F", "F", 2) if at(i - 1) == "U" and at(i - 2) in ("O", "A") and i + 2 >= len(s) else ("K", "K", 2) if i == 0 or at(i + 2) in _VOWELS else ("", "", 2)
            elif at(i + 1) in ("E", "I", "Y"):
                p, q, n = ("K", "J", 1) if i == 0 and at(i + 1, 2) in ("ER", "ES", "IL", "IN", "ET") else ("J", "K", 1)
            else:
                p, q, n = "K", "K", 2 if at(i + 1) == "G" else 1
        elif c == "H":
            sounds = at(i + 1) in _VOWELS and (i == 0 or at(i - 1) in _VOWELS) and bool(at(i + 1))
            p, q, n = ("H", "H", 2) if sounds else ("", "", 1)
        elif c == "J":
            p, q, n = ("J", "A" if i == 0 else "H" if at(i - 1) in _VOWELS and at(i + 1) in ("A", "O") else "J", 2 if at(i + 1) == "J" else 1)
        elif c == "S":
            p, q, n = ("X", "S", 3) if at(i + 1, 2) in ("IO", "IA") else ("S", "S", 2 if at(i + 1) in ("S", "Z") or at(i + 1, 2) in ("CI", "CE", "CY") else 1)
        elif c == "T":
            p, q, n = "T", "T", 2 if at(i + 1) in ("T", "D") else 1
        elif c == "W":
            p, q, n = ("A", "F", 1) if i == 0 and at(i + 1) in _VOWELS else ("R", "R", 2) if at(i + 1) == "R" else ("", "F", 1) if i == len(s) - 1 and at(i - 1) in _VOWELS else ("", "", 1)
        else:
            sound = _SINGLE.get(c, "")
            p, q, n = sound, sound, 2 if at(i + 1) == c else 1
        one, two, i = one + p, two + q, i + n
    return one[:length], two[:length]


def _pairs(fn):
    def go(a: pa.Array, b: pa.Array) -> pa.Array:
        return pa.array([None if x is None or y is None else fn(x, y) for x, y in zip(a.to_pylist(), b.to_pylist(), strict=True)], pa.float64())

    return F.arrow_udf(go, "double")


def _codes(part: int):
    def go(a: pa.Array) -> pa.Array:
        return pa.array([None if x is None else [double_metaphone_py(t)[part] for t in x.split()] for x in a.to_pylist()], pa.list_(pa.string()))

    return F.arrow_udf(go, "array<string>")


def seq_ratio(a: Column, b: Column) -> Column:
    return _pairs(seq_ratio_py)(a, b)


def jaro_winkler(a: Column, b: Column) -> Column:
    return _pairs(jaro_winkler_py)(a, b)


def phonetic(name: Column, secondary: bool = False) -> Column:
    """array<string>: the code of each token of a name."""
    return _codes(int(secondary))(name)


def norm_name(name: Column) -> Column:
    return F.lower(F.trim(F.regexp_replace(name, r"\s+", " ")))


def tokens(name: Column) -> Column:
    return F.array_distinct(F.split(norm_name(name), " "))


def token_jaccard(a: Column, b: Column) -> Column:
    return F.size(F.array_intersect(tokens(a), tokens(b))) / F.size(F.array_union(tokens(a), tokens(b)))


def phonetic_overlap(a1: Column, a2: Column, b1: Column, b2: Column) -> Column:
    """Tokens of the shorter name whose primary or secondary code stands in the other, over the longer's count."""
    short = F.size(a1) <= F.size(b1)
    x1, x2 = F.when(short, a1).otherwise(b1), F.when(short, a2).otherwise(b2)
    y = F.when(short, F.array_union(b1, b2)).otherwise(F.array_union(a1, a2))
    hits = F.size(F.filter(F.arrays_zip(x1.alias("p"), x2.alias("q")), lambda z: F.array_contains(y, z["p"]) | F.array_contains(y, z["q"])))
    return hits / F.greatest(F.size(a1), F.size(b1))


def abbrev_signal(a: Column, b: Column, mode: str = "fixed") -> Column:
    """1 where one name abbreviates the other, else 0; names must have as many parts.

    ``fixed``: every part pair is equal or a single letter with the other's initial, at least one of
    the latter. ``first_letter`` is the faulty baseline: equal first letters are enough.
    """
    x, y = (F.split(F.regexp_replace(norm_name(n), r"\.", ""), " ") for n in (a, b))
    pairs = F.arrays_zip(x.alias("x"), y.alias("y"))
    same_first = lambda p: F.substring(p["x"], 1, 1) == F.substring(p["y"], 1, 1)
    if mode == "first_letter":
        ok = F.forall(pairs, same_first)
        return F.when((F.size(x) == F.size(y)) & ok, 1.0).otherwise(0.0)
    single = lambda p: ((F.length(p["x"]) == 1) | (F.length(p["y"]) == 1)) & (p["x"] != p["y"]) & same_first(p)
    ok = F.forall(pairs, lambda p: (p["x"] == p["y"]) | single(p)) & F.exists(pairs, single)
    return F.when((F.size(x) == F.size(y)) & ok, 1.0).otherwise(0.0)


#: Transliteration families of first names (own list).
FAMILIES = (("john", "jon", "jhon"), ("alexander", "aleksandr", "alexandre"), ("yuri", "iouri", "juri"), ("stephen", "stefan", "stephan"))
ENDINGS = (("ov", "ova"), ("ev", "eva"))


def gender_pair(a: Column, b: Column, endings: tuple[tuple[str, str], ...] = ENDINGS) -> Column:
    """Whether two normalised names differ only by a Slavic gender ending."""
    hit = F.lit(False)
    for m, f in endings:
        one = a.endswith(m) & b.endswith(f) & (F.substring(a, F.lit(1), F.length(a) - len(m)) == F.substring(b, F.lit(1), F.length(b) - len(f)))
        two = b.endswith(m) & a.endswith(f) & (F.substring(b, F.lit(1), F.length(b) - len(m)) == F.substring(a, F.lit(1), F.length(a) - len(f)))
        hit = hit | one | two
    return hit


def cultural_signal(a: Column, b: Column, families: tuple[tuple[str, ...], ...] = FAMILIES) -> Column:
    """1 for a gender pair or first names of one transliteration family, else 0."""
    x, y = norm_name(a), norm_name(b)
    hit = gender_pair(x, y)
    f, g = F.split(x, " ")[0], F.split(y, " ")[0]
    for family in families:
        hit = hit | (f.isin(*family) & g.isin(*family) & (f != g))
    return F.when(hit, 1.0).otherwise(0.0)
