"""Column functions of the methods; `register` makes them SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

WHITE = r"[ \t\n\r\f]+"
NOT_LETTER = r"[^\p{L}]+"
#: Number with optional decimals, an optional multiplier or percent sign, an optional unit word.
QUANTITY = r"([-+]?[0-9]+(?:\.[0-9]+)?)\s*(%|[kKMB]\b)?\s*([\p{L}/]+)?"


def numeric_score(mine: Column, theirs: Column, direction: Column | int = 1, tolerance: Column | float = 0.0) -> Column:
    """1, 0 or -1 for better, as good within a relative tolerance, or worse; null when either is missing."""
    difference = mine - theirs
    room = tolerance * F.greatest(F.abs(mine), F.abs(theirs))
    return (
        F.when(mine.isNull() | theirs.isNull() | F.isnan(mine) | F.isnan(theirs), F.lit(None).cast("int"))
        .when(F.abs(difference) <= room, 0).when(difference * direction > 0, 1).otherwise(-1)
    )


EQUIVALENCES = ("exact", "jaccard", "edit", "cosine")


def equivalent(a: Column, b: Column, how: str = "exact", least: float = 0.5) -> Column:
    """Whether two values mean the same: equal when normalised, or as similar as `least` by tokens, edits or trigram vectors."""
    a, b = normalise_value(a), normalise_value(b)
    if how == "exact":
        return a == b
    measures = {"jaccard": lambda: overlap(tokens(a), tokens(b)), "edit": lambda: edit_similarity(a, b), "cosine": lambda: cosine(embed_text(a, unit=False), embed_text(b, unit=False))}
    return F.round(measures[how](), 6) >= least


def categorical_score(mine: Column, theirs: Column, how: str = "exact", least: float = 0.5) -> Column:
    """1 for a different value, 0 for an equivalent one, never -1; null when either is missing."""
    return F.when(mine.isNull() | theirs.isNull(), F.lit(None).cast("int")).when(equivalent(mine, theirs, how, least), 0).otherwise(1)


def normalise_value(value: Column) -> Column:
    """Lower case, runs of anything but letters and digits as one space."""
    return F.trim(F.regexp_replace(F.lower(value), r"[^\p{L}\p{N}]+", " "))


def parse_quantity(text: Column) -> Column:
    """struct(value, unit) of the first number of a text; k, M and B multiply; % and words become the unit."""
    number = F.regexp_extract(text, QUANTITY, 1).try_cast("double")
    suffix, word = F.regexp_extract(text, QUANTITY, 2), F.regexp_extract(text, QUANTITY, 3)
    scale = F.when(F.lower(suffix) == "k", 1e3).when(suffix == "M", 1e6).when(suffix == "B", 1e9).otherwise(1.0)
    return F.when(number.isNotNull(), F.struct((number * scale).alias("value"), F.nullif(F.when(suffix == "%", F.lit("%")).otherwise(F.lower(word)), F.lit("")).alias("unit")))


def words(text: Column) -> Column:
    return F.filter(F.split(text, WHITE), lambda x: x != "")


def tokens(value: Column) -> Column:
    """Distinct lower-cased tokens."""
    return F.array_distinct(F.filter(F.split(F.lower(value), WHITE), lambda x: x != ""))


def overlap(a: Column, b: Column, measure: str = "jaccard") -> Column:
    """Lexical overlap of two token arrays: jaccard, overlap, dice."""
    both = F.size(F.array_intersect(a, b)).cast("double")
    below = {"jaccard": F.size(F.array_union(a, b)), "overlap": F.least(F.size(a), F.size(b)), "dice": (F.size(a) + F.size(b)) / 2}[measure]
    return F.coalesce(F.try_divide(both, below), F.lit(0.0))


def edit_similarity(a: Column, b: Column) -> Column:
    return F.coalesce(1 - F.try_divide(F.levenshtein(a, b), F.greatest(F.length(a), F.length(b))), F.lit(1.0))


def confidence(cluster_a: Column, cluster_b: Column, high_overlap: Column, related: Column) -> Column:
    """Six levels, first match; a null cluster is noise."""
    same = (cluster_a == cluster_b) & cluster_a.isNotNull() & cluster_b.isNotNull()
    noisy = F.when(cluster_a.isNull(), 1).otherwise(0) + F.when(cluster_b.isNull(), 1).otherwise(0)
    return F.when(same & high_overlap, 5).when(same, 4).when(~related, 0).when(noisy == 0, 3).when(noisy == 1, 2).otherwise(1)


def edge_score(conf: Column, gap: Column, gamma: float = 1.0, delta: float = 1.0) -> Column:
    return F.pow(conf.cast("double"), F.lit(float(gamma))) / F.pow((gap + 1).cast("double"), F.lit(float(delta)))


def axis_score(wins: Column, draws: Column, losses: Column, alpha: float | Column = 0.5) -> Column:
    """P(win) + alpha P(draw) - P(loss); 0 when there is no verdict."""
    return F.coalesce(F.try_divide(wins + alpha * draws - losses, wins + draws + losses), F.lit(0.0))


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a) * dot(b, b)))


#: Multipliers of the three characters of a trigram, and the modulus.
TRIGRAM, TRIGRAM_MODULUS = (7919, 104729, 1299709), 1000003


def embed_text(value: Column, size: int = 64, unit: bool = True) -> Column:
    """Deterministic text vector: signed hashed character trigrams of the normalised value, counts, unit length unless told.

    The hash is arithmetic on code points, so any SQL engine gives the same vector.
    """
    codes = F.transform(F.filter(F.split(F.concat(F.lit("  "), normalise_value(value), F.lit(" ")), ""), lambda c: c != ""), lambda c: F.ascii(c).cast("bigint"))

    def grams(at: Column) -> Column:
        n = F.size(at) - 2
        times = lambda f: lambda c: c * f
        parts = [F.transform(F.slice(at, k + 1, n), times(f)) for k, f in enumerate(TRIGRAM)]
        return F.zip_with(F.zip_with(parts[0], parts[1], lambda x, y: x + y), parts[2], lambda x, y: (x + y) % TRIGRAM_MODULUS)

    def counted(hashes: Column) -> Column:
        sign = lambda h: F.when(F.floor(h / F.lit(size)) % 2 == 0, 1.0).otherwise(-1.0)
        return F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda j: F.aggregate(hashes, F.lit(0.0), lambda s, h: s + F.when(h % size == j, sign(h)).otherwise(0.0)))

    once = lambda v, then: F.element_at(F.transform(F.array(v), then), 1)
    raw = once(once(codes, grams), counted)
    if not unit:
        return raw
    length = lambda r: F.sqrt(F.aggregate(r, F.lit(0.0), lambda s, v: s + v * v))
    return once(raw, lambda r: once(length(r), lambda n: F.transform(r, lambda x: F.coalesce(F.try_divide(x, n), F.lit(0.0)))))


_SQL = {
    "numeric_score": ("mine DOUBLE, theirs DOUBLE, direction INT, tolerance DOUBLE", "INT", "CASE WHEN mine IS NULL OR theirs IS NULL THEN NULL WHEN abs(mine - theirs) <= tolerance * greatest(abs(mine), abs(theirs)) THEN 0 WHEN (mine - theirs) * direction > 0 THEN 1 ELSE -1 END"),
    "normalise_value": ("value STRING", "STRING", r"trim(regexp_replace(lower(value), '[^\\p{L}\\p{N}]+', ' '))"),
    "axis_score": ("wins BIGINT, draws BIGINT, losses BIGINT, alpha DOUBLE", "DOUBLE", "coalesce(try_divide(wins + alpha * draws - losses, wins + draws + losses), 0D)"),
    "edge_score": ("conf INT, gap INT, gamma DOUBLE, delta DOUBLE", "DOUBLE", "pow(conf, gamma) / pow(gap + 1, delta)"),
    "novelty_step": ("verdict INT, so_far BIGINT", "BIGINT", "so_far + CASE WHEN verdict = 1 THEN 1 ELSE 0 END"),
}


def register(spark: SparkSession) -> list[str]:
    """Create the temporary SQL functions; returns their names."""
    for name, (arguments, result, body) in _SQL.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {result} RETURN {body}")
    return sorted(_SQL)
