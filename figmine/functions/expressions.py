"""Column expressions of the chain: boxes, bit hashes, vectors, probabilities."""

from __future__ import annotations

from pyspark.sql import functions as F


def area(b):
    return (b["x1"] - b["x0"]) * (b["y1"] - b["y0"])


def iou(a, b):
    """Overlap of two boxes by their union; 0 where the union is empty."""
    zero = F.lit(0.0)
    inter = F.greatest(zero, F.least(a["x1"], b["x1"]) - F.greatest(a["x0"], b["x0"])) * F.greatest(zero, F.least(a["y1"], b["y1"]) - F.greatest(a["y0"], b["y0"]))
    union = area(a) + area(b) - inter
    return F.when(union > 0, inter / union).otherwise(zero)


def hamming(a, b):
    """Differing bits of two hashes held as structs of three 64-bit words."""
    return sum((F.bit_count(a[w].bitwiseXOR(b[w])) for w in ("w1", "w2")), F.bit_count(a["w0"].bitwiseXOR(b["w0"])))


def word_from_hex(text, start: int, digits: int):
    """``digits`` (16 or 4) hex digits as a signed 64-bit number."""
    part = lambda s, n: F.conv(F.substring(text, s, n), 16, 10).cast("long")
    if digits <= 8:
        return part(start, digits)
    return F.shiftleft(part(start, 8), 32).bitwiseOR(part(start + 8, digits - 8))


def pack_words(text):
    """36 hex digits as three words; the last one holds 16 bits."""
    return F.struct(word_from_hex(text, 1, 16).alias("w0"), word_from_hex(text, 17, 16).alias("w1"), word_from_hex(text, 33, 4).alias("w2"))


def band_keys(text, bands: int, bits: int):
    """array<struct(band, value)> of consecutive hex digits; ``bits`` is a multiple of 4."""
    width = bits // 4
    return F.array(*[F.struct(F.lit(k).cast("tinyint").alias("band"), F.substring(text, 1 + k * width, width).alias("value")) for k in range(bands)])


def dot(a, b):
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a):
    return F.sqrt(dot(a, a))


def l2_normalize(a):
    n = norm(a)
    return F.when(n > 0, F.transform(a, lambda x: x / n))


def cosine(a, b):
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n)


def mean_logprob(tokens):
    return F.when(F.size(tokens) > 0, F.aggregate(tokens, F.lit(0.0), lambda s, x: s + x) / F.size(tokens))


def linear_prob(tokens):
    """Geometric mean of the token probabilities."""
    return F.exp(mean_logprob(tokens))


def register(spark) -> None:
    """The same functions for SQL."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hamming_words(a STRUCT<w0: BIGINT, w1: BIGINT, w2: BIGINT>, b STRUCT<w0: BIGINT, w1: BIGINT, w2: BIGINT>) RETURNS INT RETURN bit_count(a.w0 ^ b.w0) + bit_count(a.w1 ^ b.w1) + bit_count(a.w2 ^ b.w2)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cosine_sim(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x) / sqrt(aggregate(a, 0D, (s, x) -> s + x * x) * aggregate(b, 0D, (s, x) -> s + x * x))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION linear_prob(t ARRAY<DOUBLE>) RETURNS DOUBLE RETURN exp(aggregate(t, 0D, (s, x) -> s + x) / size(t))")
