"""Column expressions; all stay in the JVM, and those on scalars stay inside generated code."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(x: Column, weights, unroll: int = 64) -> Column:
    """Sum of x[i] * weights[i]. Short vectors are unrolled, which keeps them inside whole-stage code."""
    weights = [float(w) for w in weights]
    if len(weights) <= unroll:
        out = F.lit(0.0)
        for i, w in enumerate(weights):
            out = out + F.get(x, F.lit(i)) * F.lit(w)
        return out
    return F.aggregate(F.zip_with(x, F.array(*[F.lit(w) for w in weights]), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_scale(a: Column, s) -> Column:
    s = s if isinstance(s, Column) else F.lit(float(s))
    return F.transform(a, lambda x: x * s)


def vec_norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x))


def sigmoid(m: Column) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-m))


def log_loss(m: Column, y: Column) -> Column:
    """log(1 + e^m) - y m without overflow."""
    return F.log1p(F.exp(-F.abs(m))) + F.greatest(m, F.lit(0.0)) - y * m


def softmax(ms: list[Column]) -> list[Column]:
    top = F.greatest(*ms) if len(ms) > 1 else ms[0]
    parts = [F.exp(m - top) for m in ms]
    total = parts[0]
    for p in parts[1:]:
        total = total + p
    return [p / total for p in parts]


def argmax(ms: list[Column]) -> Column:
    """Number of the first largest value."""
    arr = F.array(*ms)
    return F.array_position(arr, F.array_max(arr)).cast("int") - 1


def one_hot(col: Column, vocabulary: list) -> list[Column]:
    return [F.coalesce((col == F.lit(v)).cast("double"), F.lit(0.0)) for v in vocabulary]


def vocabulary_index(col: Column, vocabulary: list) -> Column:
    """Place of a value in the vocabulary by a map lookup, null if it isn't there."""
    return F.try_element_at(F.create_map(*[F.lit(x) for i, v in enumerate(vocabulary) for x in (v, i)]), col)


def standardize(col: Column, mean: float, std: float) -> Column:
    """A feature without spread is only centred."""
    return (col - F.lit(float(mean))) / F.lit(float(std) if std and std > 0 else 1.0)


def hash_key(col: Column, salt: str | None = None) -> Column:
    """Hexadecimal SHA-256. Without a salt small integers can be guessed from their digests."""
    text = col.cast("string")
    return F.sha2((F.concat(F.lit(salt), text) if salt else text).cast("binary"), 256)


def _runs(parts) -> list:
    """Columns, and lists of the constants between them: a run of constants is joined once and not in every row."""
    out = []
    for p in parts:
        if isinstance(p, Column):
            out.append(p)
        elif out and isinstance(out[-1], list):
            out[-1].append(p)
        else:
            out.append([p])
    return out


def hash_uniform(*parts) -> Column:
    """A number in (0, 1) from 52 bits of a digest of the parts; other engines can compute the same."""
    cols = [p if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    digest = F.sha2(F.concat_ws("|", *[c.cast("string") for c in cols]).cast("binary"), 256)
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)


def hash_number(*parts) -> Column:
    """A number below 2**60 from a digest of the parts; other engines can compute the same."""
    cols = [p if isinstance(p, Column) else F.lit("|".join(str(x) for x in p)) for p in _runs(parts)]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[c.cast("string") for c in cols]).cast("binary")), 1, 15), 16, 10).cast("long")


def laplace_from_uniform(u: Column, std: float) -> Column:
    """Inverse distribution function of the Laplace law with the given standard deviation."""
    b = std / 2**0.5
    return F.when(u < 0.5, F.lit(b) * F.log(2 * u)).otherwise(F.lit(-b) * F.log(2 * (1 - u)))


def logistic_from_uniform(u: Column) -> Column:
    return F.log(u / (1 - u))


def days_since(ts: Column, base: str) -> Column:
    """Days, with fractions, from a date to a timestamp without zone."""
    moment = F.to_timestamp_ntz(F.lit(base))
    return (F.timestamp_diff("SECOND", moment, ts) / 86400.0).cast("double")


def json_number(col: Column, path: str) -> Column:
    return F.get_json_object(col, path).try_cast("double")


def tokens(text: Column) -> Column:
    clean = F.trim(F.regexp_replace(F.lower(text), "[^\\p{L}\\p{N}]+", " "))
    return F.when(F.length(clean) > 0, F.split(clean, " ")).otherwise(F.array().cast("array<string>"))


def hash_text(text: Column, dim: int = 64) -> Column:
    """Array of ``dim`` doubles: signed counts of hashed tokens over the root of the number of tokens. A stand-in for a
    pretrained encoder, with nothing to download."""
    hashes = F.transform(tokens(text), lambda w: F.xxhash64(w))
    n = F.greatest(F.size(hashes), F.lit(1)).cast("double")
    zero = F.array_repeat(F.lit(0.0), dim)

    def add(acc, h):
        place = F.pmod(h, F.lit(dim)).cast("int")
        sign = F.when(F.shiftright(h, 62).bitwiseAND(F.lit(1)) == 1, F.lit(1.0)).otherwise(F.lit(-1.0))
        return F.transform(acc, lambda v, i: F.when(i == place, v + sign).otherwise(v))

    return vec_scale(F.aggregate(hashes, zero, add), 1 / F.sqrt(n))


def name_words(col: Column) -> Column:
    return F.split(F.trim(col), " +")
