"""Native text expressions: tokens, character shares, seeded keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TOKEN = r"[\p{L}\p{N}]+"
#: Signs that count as clean besides letters, marks, digits, underscore and white space, with full-width twins.
CLEAN_SIGNS = ".,;!?()/，．；！？（）／。"
#: Further clean signs by field.
FIELD_SIGNS = {"math": r"+\-*=<>^%|\[\]{}$\\°±×÷≤≥≠∑∫√π", "code": r"{}\[\]<>=+\-*&|^%$#@~`'\":\\"}


def col(c: str | Column) -> Column:
    return F.col(c) if isinstance(c, str) else c


def tokens(c: str | Column) -> Column:
    return F.regexp_extract_all(F.lower(col(c)), F.lit(TOKEN), F.lit(0))


def once(value: Column, use) -> Column:
    """use(value) with value evaluated once, however often it is used: it is bound to a variable of a higher-order function."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def explode_rows(df: DataFrame, keep: list, items: Column, name: str) -> DataFrame:
    """(*keep, name): one row per non-null item.

    An inner explode lets the optimiser test the array's size below it, which evaluates a costly array twice; the
    outer form does not.
    """
    return df.select(*keep, F.explode_outer(items).alias(name)).where(F.col(name).isNotNull())


def seeded_key(c: str | Column, seed: int | str = 42) -> Column:
    """A sort key that shuffles ids the same way on every engine."""
    return F.md5(F.concat(F.lit(f"{seed}:"), col(c).cast("string")))


def seeded_uniform(c: str | Column, salt: str = "42") -> Column:
    """A uniform number in [0, 1) from an id."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{salt}:"), col(c).cast("string"))), 1, 8), 16, 10).cast("double") / 4294967296.0


def fine_uniform(c: str | Column, salt: str = "42") -> Column:
    """As seeded_uniform, with 52 bits instead of 32, for draws over more than a billion rows."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{salt}:"), col(c).cast("string"))), 1, 13), 16, 10).cast("double") / float(1 << 52)


def noise_class(*fields: str, unicode_word: bool = True) -> str:
    """The regular expression of characters that count as noise, with the fields' signs allowed."""
    word = r"\p{L}\p{M}\p{N}_" if unicode_word else r"\w"
    return "[^" + word + r"\s" + CLEAN_SIGNS + "".join(FIELD_SIGNS[f] for f in fields) + "]"


def unicode_words(pattern: str) -> str:
    r"""The pattern with \w spelt out, as the engines' own \w is ASCII."""
    out, in_class, i = [], False, 0
    while i < len(pattern):
        two = pattern[i : i + 2]
        if two == r"\w":
            out.append(r"\p{L}\p{M}\p{N}_" if in_class else r"[\p{L}\p{M}\p{N}_]")
            i += 2
            continue
        if two[:1] == "\\":
            out.append(two)
            i += 2
            continue
        if two[:1] == "[":
            in_class = True
        elif two[:1] == "]":
            in_class = False
        out.append(two[:1])
        i += 1
    return "".join(out)


def share_of(c: str | Column, pattern: str) -> Column:
    """Characters that match, over all characters; 0 for empty text. Runs are removed at once."""
    t = col(c)
    n = F.length(t)
    return F.when(n > 0, (n - F.length(F.regexp_replace(t, f"(?:{pattern})+", ""))) / n).otherwise(F.lit(0.0))


def latin_share(c: str | Column) -> Column:
    return share_of(c, "[A-Za-z]")


def lead_line(c: str | Column) -> Column:
    return F.split(col(c), "\n", 2)[0]


def rest_lines(c: str | Column) -> Column:
    return F.coalesce(F.get(F.split(col(c), "\n", 2), F.lit(1)), F.lit(""))


def dot(a: str | Column, b: str | Column) -> Column:
    return F.aggregate(F.zip_with(col(a), col(b), lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: str | Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: str | Column, b: str | Column) -> Column:
    """Cosine of two arrays; 0 if either is all zero."""
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n).otherwise(F.lit(0.0))


def squared_distance(a: str | Column, b: str | Column) -> Column:
    return F.aggregate(F.zip_with(col(a), col(b), lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x)


def unique_share(c: str | Column) -> Column:
    """Different tokens over tokens; 0 without tokens."""
    t = tokens(c)
    return F.when(F.size(t) > 0, F.size(F.array_distinct(t)) / F.size(t)).otherwise(F.lit(0.0))


SQL_FUNCTIONS = {
    "en_ratio": "(t STRING) RETURNS DOUBLE RETURN if(length(t) > 0, (length(t) - length(regexp_replace(t, '[A-Za-z]+', ''))) / length(t), 0)",
    "noise_ratio": r"(t STRING) RETURNS DOUBLE RETURN if(length(t) > 0, (length(t) - length(regexp_replace(t, '[^\\p{L}\\p{M}\\p{N}_\\s.,;!?()/，．；！？（）／。]+', ''))) / length(t), 0)",
    "md5_uniform": "(id STRING, salt STRING) RETURNS DOUBLE RETURN cast(conv(substr(md5(concat(salt, ':', id)), 1, 8), 16, 10) AS DOUBLE) / 4294967296D",
    "cosine_of": "(a ARRAY<FLOAT>, b ARRAY<FLOAT>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> cast(x AS DOUBLE) * cast(y AS DOUBLE)), 0D, (s, x) -> s + x) / nullif(sqrt(aggregate(transform(a, x -> cast(x AS DOUBLE) * cast(x AS DOUBLE)), 0D, (s, x) -> s + x)) * sqrt(aggregate(transform(b, x -> cast(x AS DOUBLE) * cast(x AS DOUBLE)), 0D, (s, x) -> s + x)), 0D)",
    "minmax_of": "(x DOUBLE, lo DOUBLE, hi DOUBLE) RETURNS DOUBLE RETURN if(hi > lo, (x - lo) / (hi - lo), 0D)",
    "ifd_of": "(given DOUBLE, alone DOUBLE) RETURNS DOUBLE RETURN given / nullif(alone, 0D)",
}


def register_sql_functions(spark: SparkSession) -> None:
    """Publishes the expressions to SQL as temporary functions, which the optimiser inlines."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
