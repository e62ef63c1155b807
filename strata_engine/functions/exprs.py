"""Column expressions: portable uniforms, vectors, kernels, text and time features. All run in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

GAMMAS = (0.001, 0.01, 0.1, 1.0, 10.0)
UNIT_GAMMA = 0.5


def _c(x) -> Column:
    return x if isinstance(x, Column) else F.col(x)


def r6(x) -> Column:
    """Rounded to six digits, without negative zero."""
    return F.round(_c(x), 6) + F.lit(0.0)


def r9(x) -> Column:
    return F.round(_c(x), 9) + F.lit(0.0)


def hash_bits(*parts, digits: int = 13) -> Column:
    """The first hex digits of md5(parts joined by '|') as a number; the same in every engine."""
    text = F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, digits), 16, 10).cast("long")


def portable_u(seed, purpose, *ids) -> Column:
    """Uniform in [0, 1), keyed by seed, purpose and ids: independent of partitions, engine and order."""
    return hash_bits(seed, purpose, *ids).cast("double") / F.lit(float(1 << 52))


def vec(x) -> Column:
    return _c(x).cast("array<double>")


def total(x) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda a, v: a + v)


def dot(a, b) -> Column:
    return total(F.zip_with(_c(a), _c(b), lambda x, y: x * y))


def sqdist(a, b) -> Column:
    return total(F.zip_with(_c(a), _c(b), lambda x, y: (x - y) * (x - y)))


def rbf(a, b, gamma: float = UNIT_GAMMA) -> Column:
    return F.exp(-F.lit(gamma) * sqdist(a, b))


def rbf_mix(a, b, gammas=GAMMAS) -> Column:
    """Sum, not mean, over the bandwidths; the distance is computed once for all of them."""
    return F.aggregate(F.array(*[F.lit(g) for g in gammas]), F.struct(F.lit(0.0).alias("s"), sqdist(a, b).alias("d")), lambda acc, g: F.struct((acc["s"] + F.exp(-g * acc["d"])).alias("s"), acc["d"].alias("d")), lambda acc: acc["s"])


def minus(a, mu) -> Column:
    return F.zip_with(_c(a), _c(mu), lambda x, m: x - m)


def quadratic(a, b, mu) -> Column:
    """Squared inner product of vectors less their mean."""
    return F.pow(dot(minus(a, mu), minus(b, mu)), F.lit(2.0))


def quadratic_map(a, mu, d: int) -> Column:
    """The exact finite map of ``quadratic``: squares, then sqrt(2) times the products of different components."""
    x = minus(a, mu)
    return F.array(*[x[i] * x[i] for i in range(d)], *[F.lit(2.0**0.5) * x[i] * x[j] for i in range(d) for j in range(i + 1, d)])


def l2_normalise(a) -> Column:
    n = F.sqrt(dot(a, a))
    return F.when(n > 0, F.transform(_c(a), lambda x: x / n)).otherwise(_c(a))


def clip(a, lo: float, hi: float) -> Column:
    return F.transform(_c(a), lambda x: F.least(F.greatest(x, F.lit(lo)), F.lit(hi)))


def one_hot(x, values) -> Column:
    return F.array(*[F.when(_c(x) == v, 1.0).otherwise(0.0) for v in values])


def linear_map(a, matrix) -> Column:
    """Rows of ``matrix`` against the vector."""
    return F.array(*[dot(a, F.array(*[F.lit(float(v)) for v in row])) for row in matrix])


def finite(a, d: int | None = None) -> Column:
    """Whether a vector is whole: not null, of length ``d``, without null, NaN or infinite components."""
    ok = F.coalesce(~F.exists(_c(a), lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))), F.lit(False))
    return ok & (F.size(_c(a)) == d) if d is not None else ok


def text_features(t) -> dict[str, Column]:
    """Eight surface features of a text; letters, digits and signs are ASCII, so that engines agree."""
    t = F.coalesce(_c(t), F.lit(""))
    words = F.filter(F.split(t, "[ \n\t]+"), lambda w: w != "")
    lines = F.filter(F.split(t, "\n"), lambda w: w != "")
    n, k = F.length(t).cast("double"), F.size(words).cast("double")
    safe = F.greatest(n, F.lit(1.0))
    return {
        "ln_chars": F.log(n + 1), "ln_words": F.log(k + 1), "mean_word": F.when(k > 0, F.aggregate(words, F.lit(0.0), lambda a, w: a + F.length(w)) / k).otherwise(0.0),
        "digit_ratio": F.regexp_count(t, F.lit("[0-9]")) / safe, "punct_ratio": F.regexp_count(t, F.lit("[!-/:-@]")) / safe, "upper_ratio": F.regexp_count(t, F.lit("[A-Z]")) / safe,
        "distinct_ratio": F.when(k > 0, F.size(F.array_distinct(words)) / k).otherwise(0.0), "repeat_ratio": F.when(F.size(lines) > 0, 1 - F.size(F.array_distinct(lines)) / F.size(lines)).otherwise(0.0),
    }
