"""Vector expressions on array columns, and deterministic word embeddings."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    """Inner product; the reference form, kept for small inputs (Arrow blocks score the rest)."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0).cast("double"), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def neg_l2(a: Column, b: Column) -> Column:
    """Euclidean distance, negated so that higher is better."""
    return -F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0).cast("double"), lambda s, x: s + x))


def quantise(v: Column, scale: int = 127) -> Column:
    """Whole-number twin of a unit vector; its inner products are exact in any engine."""
    return F.transform(v, lambda x: F.floor(x.cast("double") * scale + 0.5).cast("double"))


def sign_vector(text: Column, d: int = 128) -> Column:
    """+1 or -1 for each bit of salted md5 digests of a text."""
    bits = F.concat(*(F.md5(F.concat(text, F.lit(f"#{b}"))) for b in range(-(-d // 128))))
    nibble = lambda i: F.conv(F.substring(bits, (i / 4).cast("int") + 1, F.lit(1)), 16, 10).cast("int")
    return F.transform(
        F.sequence(F.lit(0), F.lit(d - 1)),
        lambda i: F.when(F.floor(nibble(i) / F.element_at(F.array(*map(F.lit, (8, 4, 2, 1))), i % 4 + 1)) % 2 == 1, 1.0).otherwise(-1.0),
    )
