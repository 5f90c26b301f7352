"""Headers in two surface forms, and faulty ones."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..schema import FEATURES, PRIMARY_MASK


def render_header(bits: Column, form: Column | str) -> Column:
    """The header of an intent: special tokens in delimiters, or one comment line of words; '' for no feature."""
    on = lambda b: bits.bitwiseAND(1 << b) != 0
    token = F.concat_ws(" ", F.lit("<WANT>"), *[F.when(on(b), f"<{n}>") for n, b, _, _ in FEATURES], F.lit("</WANT>"))
    words = F.concat(F.lit("# wants: "), F.concat_ws(", ", *[F.when(on(b), w) for _, b, _, w in FEATURES]))
    form = F.lit(form) if isinstance(form, str) else form
    return F.when(F.coalesce(bits, F.lit(0)) == 0, "").when(form == "token", token).otherwise(words)


def _pick(key: Column, n: int) -> Column:
    return (F.conv(F.substring(F.md5(key.cast("binary")), 1, 8), 16, 10).cast("long") % n).cast("int")


def corrupt(bits: Column, key: Column, k: int = 1) -> Column:
    """Flip k primary features chosen by the key; THIN and TALL never both hold afterwards (the newly set one wins)."""
    first = _pick(F.concat(F.lit("c1:"), key), 4)
    second = (first + 1 + _pick(F.concat(F.lit("c2:"), key), 3)) % 4
    mask = F.lit(0)
    for i in range(4):
        mask = mask + F.when((first == i) | ((second == i) if k > 1 else F.lit(False)), 1 << i).otherwise(0)
    out = bits.bitwiseXOR(mask)
    both = out.bitwiseAND(12) == 12
    return F.when(both & (bits.bitwiseAND(4) != 0), out.bitwiseAND(~4)).when(both, out.bitwiseAND(~8)).otherwise(out)


def random_header(bits: Column, key: Column) -> Column:
    """A feature set of the same primary size chosen by the key alone (at most three; never THIN with TALL)."""
    size = F.bit_count(bits.bitwiseAND(PRIMARY_MASK))
    singles, doubles, triples = (1, 2, 4, 8), (3, 5, 9, 6, 10), (7, 11)
    choose = lambda opts, tag: F.element_at(F.array(*map(F.lit, opts)), _pick(F.concat(F.lit(tag), key), len(opts)) + 1)
    return F.when(size == 1, choose(singles, "r1:")).when(size == 2, choose(doubles, "r2:")).when(size >= 3, choose(triples, "r3:")).otherwise(0)


def dropout(header: Column, key: Column, p: float = 0.5) -> Column:
    """The header, emptied with probability p by the key (null-mode training rows)."""
    return F.when(_pick(F.concat(F.lit("drop:"), key), 10_000) < int(p * 10_000), "").otherwise(header)
