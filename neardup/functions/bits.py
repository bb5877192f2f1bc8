"""Column expressions over packed bits: arrays of longs that hold 32 bits each, lowest bit first."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD = 32


def hamming(a: str | Column, b: str | Column) -> Column:
    """Number of differing bits of two packed bit strings."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y)).cast("int")), F.lit(0), lambda s, x: s + x)


def bit(words: str | Column, p: int) -> Column:
    """Bit ``p`` as 0 or 1."""
    words = F.col(words) if isinstance(words, str) else words
    return F.shiftright(words[p // WORD], p % WORD).bitwiseAND(1)


def pack(flags: list[Column]) -> Column:
    """Boolean columns as packed bits."""
    words = []
    for s in range(0, len(flags), WORD):
        word = F.lit(0).cast("long")
        for j, f in enumerate(flags[s : s + WORD]):
            word = word + F.when(f, F.lit(1 << j).cast("long")).otherwise(F.lit(0).cast("long"))
        words.append(word)
    return F.array(*words)


def pack_array(flags: Column, n: int) -> Column:
    """An array of ``n`` booleans as packed bits, by one loop instead of ``n`` expressions."""
    value = lambda s: F.aggregate(
        F.sequence(F.lit(0), F.lit(min(WORD, n - s) - 1)),
        F.lit(0).cast("long"),
        lambda acc, j: acc + F.when(F.get(flags, j + s), F.pow(F.lit(2), j).cast("long")).otherwise(F.lit(0).cast("long")),
    )
    return F.array(*(value(s) for s in range(0, n, WORD)))


def chosen(words: str | Column, positions: list[int]) -> Column:
    """The bits at ``positions``, packed anew."""
    out = []
    for s in range(0, len(positions), WORD):
        word = F.lit(0).cast("long")
        for j, p in enumerate(positions[s : s + WORD]):
            word = word + F.shiftleft(bit(words, p), j)
        out.append(word)
    return F.array(*out)


def group_value(words: str | Column, start: int, width: int) -> Column:
    """The ``width`` bits from ``start`` as a number, lowest bit first."""
    words = F.col(words) if isinstance(words, str) else words
    out, at, shift = F.lit(0).cast("long"), start, 0
    while shift < width:
        off = at % WORD
        take = min(WORD - off, width - shift)
        part = F.shiftright(words[at // WORD], off).bitwiseAND((1 << take) - 1)
        out = out + F.shiftleft(part, shift)
        at, shift = at + take, shift + take
    return out
