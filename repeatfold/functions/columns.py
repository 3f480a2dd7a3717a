"""Column expressions: typing, decoding and the gate without Python on the executors."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def left_greedy(starts: Column, length: Column, after: Column | None = None) -> Column:
    """Disjoint starts beyond ``after``, from left to right; ``starts`` in any order."""
    free = F.array_min(starts).cast("long") if after is None else after.cast("long") + 1
    init = F.struct(free.alias("free"), F.array().cast("array<bigint>").alias("out"))
    step = lambda a, s: F.when(s >= a["free"], F.struct((s + length).cast("long").alias("free"), F.concat(a["out"], F.array(s.cast("long"))).alias("out"))).otherwise(a)
    return F.aggregate(F.array_sort(starts), init, step, lambda a: a["out"])


def kind_one(starts: Column, length: Column) -> Column:
    """The second start if it overlaps the first, else null."""
    s = F.array_sort(starts)
    return F.when((F.size(s) > 1) & (F.get(s, F.lit(0)) + length > F.get(s, F.lit(1))), F.get(s, F.lit(1)))


def end_bound(starts: Column, length: Column) -> Column:
    """Last cell of the overlapping second copy, or of the leftmost one."""
    return F.coalesce(kind_one(starts, length), F.array_min(starts)) + length - 1


def typed(starts: Column, length: Column) -> Column:
    """array<struct<pos, type>> of all starts in order; the leftmost has type 0."""
    one, rest = kind_one(starts, length), left_greedy(starts, length, end_bound(starts, length))
    first = F.array_min(starts)
    kind = lambda p: F.when(p == first, 0).when(p.eqNullSafe(one), 1).when(F.array_contains(rest, p), F.when(F.size(rest) == 1, 2).otherwise(3)).otherwise(4)
    return F.transform(F.array_sort(starts), lambda p: F.struct(p.alias("pos"), kind(p).alias("type")))


def gate(length: Column, s: Column, alpha: Column | float, beta: Column | float) -> Column:
    """length >= alpha / s + beta; without a copy (s = 0) false unless alpha is 0."""
    a, b = (x if isinstance(x, Column) else F.lit(float(x)) for x in (alpha, beta))
    return F.when(s == 0, (a == 0) & (length >= b)).otherwise(length >= a / F.greatest(s, F.lit(1)) + b)


def unfold_text(residual: Column, factors: Column, kinds: Column) -> Column:
    """The text behind a triple. A copy that overlaps itself is the repetition of what lies between its source and its end."""
    init = F.struct(F.lit("").alias("out"), F.lit(0).alias("h"), F.lit(0).alias("f"), F.array().cast("array<struct<k:int,a:bigint,len:int>>").alias("known"))

    def step(a: Column, c: Column) -> Column:
        kind = F.get(kinds, a["h"])
        seen = F.get(F.filter(a["known"], lambda x: x["k"] == kind), F.lit(0))
        fresh = F.get(factors, a["f"])
        use = F.when((kind > 2) & seen.isNotNull(), F.struct(kind.alias("k"), seen["a"].alias("a"), seen["len"].alias("len"))).otherwise(F.struct(kind.alias("k"), fresh["a"].alias("a"), fresh["len"].alias("len")))
        src = F.when(kind == 1, F.length(a["out"]) - use["a"]).otherwise(use["a"] - 1).cast("int")
        gap = F.length(a["out"]) - src
        plain = F.substring(a["out"], src + 1, use["len"])
        looped = F.substring(F.repeat(F.substring(a["out"], src + 1, gap), (use["len"] / gap + 1).cast("int")), F.lit(1), use["len"])
        copy = F.when(gap >= use["len"], plain).otherwise(looped)
        new = (kind <= 2) | seen.isNull()
        mark = F.struct(
            F.concat(a["out"], copy).alias("out"), (a["h"] + 1).alias("h"), (a["f"] + new.cast("int")).alias("f"),
            F.when((kind > 2) & seen.isNull(), F.concat(a["known"], F.array(use))).otherwise(a["known"]).alias("known"),
        )
        letter = F.struct(F.concat(a["out"], _char(c)).alias("out"), a["h"].alias("h"), a["f"].alias("f"), a["known"].alias("known"))
        return F.when(c == -1, a).when(c == -2, mark).otherwise(letter)

    return F.aggregate(residual, init, step, lambda a: a["out"])


def _char(code: Column) -> Column:
    """The character of a code point, from its UTF-8 bytes."""
    byte = lambda x: F.lpad(F.hex(x), 2, "0")
    rest = lambda k: byte(F.shiftright(code, k).bitwiseAND(63) + 128)
    u = (
        F.when(code < 0x80, byte(code))
        .when(code < 0x800, F.concat(byte(F.shiftright(code, 6) + 192), rest(0)))
        .when(code < 0x10000, F.concat(byte(F.shiftright(code, 12) + 224), rest(6), rest(0)))
        .otherwise(F.concat(byte(F.shiftright(code, 18) + 240), rest(12), rest(6), rest(0)))
    )
    return F.decode(F.unhex(u), "UTF-8")
