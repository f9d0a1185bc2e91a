"""Fixed-width bit masks as BIGINT columns of 62 bits each.

62 rather than 64 keeps the sign bit clear, so every engine prints the same numbers, and ``bit_or`` on plain columns
aggregates partially inside generated code.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = 62
FULL = (1 << WORD) - 1
_PRIME = 2147483647
#: Multipliers and offsets of the vertex hashes, all below 2**31.
HASHES = ((1103515245, 12345), (214013, 2531011), (48271, 1299709), (69621, 7919))


def n_words(bits: int) -> int:
    """Words that hold ``bits`` bits."""
    return max(1, -(-bits // WORD))


def names(prefix: str, words: int) -> list[str]:
    """Column names of a mask."""
    return [f"{prefix}{w}" for w in range(words)]


def to_words(bits: list[int], words: int) -> list[int]:
    """Driver side: the words of a mask with these bits set."""
    out = [0] * words
    for b in bits:
        out[b // WORD] |= 1 << (b % WORD)
    return out


def bit_word(bit: Column, word: int) -> Column:
    """Word ``word`` of the mask with the single bit ``bit``."""
    inside = bit - F.lit(word * WORD)
    return F.when((inside >= 0) & (inside < WORD), F.call_function("shiftleft", F.lit(1).cast("long"), inside.cast("int"))).otherwise(F.lit(0).cast("long"))


def hash_bit(vid: Column, bits: int, j: int = 0) -> Column:
    """The bit of hash function ``j`` for a dense id below 1e9; the same integers in any engine."""
    a, b = HASHES[j]
    return ((vid * F.lit(a).cast("long") + F.lit(b)) % F.lit(_PRIME)) % F.lit(bits)


def hash_bit_sql(vid: str, bits: int, j: int = 0) -> str:
    """SQL text of :func:`hash_bit`."""
    a, b = HASHES[j]
    return f"((({vid}) * {a} + {b}) % {_PRIME}) % {bits}"


def vertex_words(vid: Column, bits: int, n_hash: int = 1) -> list[Column]:
    """Words of a vertex's own bits, one for each hash function."""
    return [reduce(lambda a, b: a.bitwiseOR(b), [bit_word(hash_bit(vid, bits, j), w) for j in range(n_hash)]) for w in range(n_words(bits))]


def _all(conditions: list[Column]) -> Column:
    return reduce(lambda a, b: a & b, conditions)


def mask_contains(a: list[Column], b: list[Column]) -> Column:
    """Every bit of ``b`` is in ``a``."""
    return _all([x.bitwiseAND(y) == y for x, y in zip(a, b, strict=True)])


def mask_disjoint(a: list[Column], b: list[Column]) -> Column:
    return _all([x.bitwiseAND(y) == 0 for x, y in zip(a, b, strict=True)])


def mask_or(*masks: list[Column]) -> list[Column]:
    return [reduce(lambda a, b: a.bitwiseOR(b), ws) for ws in zip(*masks, strict=True)]


def mask_minus(a: list[Column], b: list[Column]) -> list[Column]:
    return [x.bitwiseAND(F.bitwise_not(y)) for x, y in zip(a, b, strict=True)]


def mask_empty(a: list[Column]) -> Column:
    return _all([x == 0 for x in a])


def mask_equal(a: list[Column], b: list[Column]) -> Column:
    return _all([x == y for x, y in zip(a, b, strict=True)])


def mask_to_bits(a: list[Column]) -> Column:
    """Array of the positions set, ascending."""
    spots = F.sequence(F.lit(0), F.lit(WORD - 1))
    has = lambda x: lambda i: F.call_function("shiftright", x, i).bitwiseAND(F.lit(1)) == 1
    shifted = lambda w: lambda i: i + w * WORD
    return F.concat(*[F.transform(F.filter(spots, has(x)), shifted(w)) for w, x in enumerate(a)])


def mask_string(a: list[Column], bits: int) -> Column:
    """0 and 1 in bit order, first bit leftmost."""
    at = [F.call_function("shiftright", a[i // WORD], F.lit(i % WORD)).bitwiseAND(F.lit(1)).cast("string") for i in range(bits)]
    return F.concat(*at)


def fold(words: list[Column], bits: int) -> list[Column]:
    """The mask of labels folded to ``bits`` (31 or a multiple of 62): bit i goes to i modulo ``bits``."""
    if bits == WORD // 2:
        one = reduce(lambda a, b: a.bitwiseOR(b), words)
        return [one.bitwiseAND(F.lit((1 << 31) - 1)).bitwiseOR(F.call_function("shiftright", one, F.lit(31)))]
    n = n_words(bits)
    return [reduce(lambda a, b: a.bitwiseOR(b), words[w::n]) if words[w::n] else F.lit(0).cast("long") for w in range(n)]
