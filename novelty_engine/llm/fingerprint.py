"""Order-independent document fingerprints by a homomorphic multiset hash.

A text is a multiset of units: paragraphs, cut further at clause and sentence ends so that an edit
touches few of them.  Each unit is hashed to a wide vector and the vectors are added modulo powers
of two, so equal multisets have equal sums in any order, and adding or taking away a unit adds or
subtracts its vector (`combine`).  The vector has two parts:

* `DENSE` lanes of 60-bit hashes modulo 2**60, which decide equality;
* 126 counting lanes modulo 2**32, one for each of 63 bits of two hashes.  With the number of units
  they estimate the cosine of two multisets: the likeness, 0 to 1.

Counting lanes are summed three to a long, which is exact below 2**21 units; a longer text sums each
lane apart.  Everything is DataFrame expressions: no Python runs on the executors.  Null and empty
texts have no unit and the zero fingerprint; two such are alike (1), one such and another are not (0).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.scan import neighbours
from .common import cut_lineage, table

DENSE = 4
UNIT_ENDS = r"[,.;:!?]+\s+|\s*\n+\s*"
SEEDS, SHIFTS = (101, 102), 21
_TRIPLE = 1 | 1 << 21 | 1 << 42
_LOW21, _LOW32, _LOW60, _LOW63 = (1 << 21) - 1, (1 << 32) - 1, (1 << 60) - 1, (1 << 63) - 1
#: From this many units on lanes are summed apart.
APART = 1 << 21


def units_of(text: Column) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), UNIT_ENDS), lambda x: x != "")


def with_lanes(df: DataFrame, **texts: str) -> DataFrame:
    """Add array<bigint> columns, one for each name=text column: the number of units, DENSE sums, then 126 counts.

    Units, their hashes and the packed sums are columns of their own, and each is used by many expressions, so
    the optimizer keeps them as separate projections and evaluates them once a row.
    """

    def dense(name: str, seed: int) -> Column:
        return F.aggregate(f"{name}_units", F.lit(0).cast("bigint"), lambda a, u: (a + F.xxhash64(u, F.lit(seed)).bitwiseAND(F.lit(_LOW60))).bitwiseAND(F.lit(_LOW60)))

    def packed(values: str, at: int) -> Column:
        return F.aggregate(F.col(values), F.lit(0).cast("bigint"), lambda a, h: (a + F.call_function("shiftrightunsigned", h, F.lit(at)).bitwiseAND(F.lit(_TRIPLE))).bitwiseAND(F.lit(_LOW63)))

    def apart(values: str) -> Column:
        bit = lambda i: (F.floor(i / 3) + i % 3 * SHIFTS).cast("int")
        one = lambda i: F.aggregate(F.col(values), F.lit(0).cast("bigint"), lambda a, h: a + F.call_function("shiftrightunsigned", h, bit(i)).bitwiseAND(F.lit(1)))
        return F.transform(F.sequence(F.lit(0), F.lit(3 * SHIFTS - 1)), one)

    def counts(name: str) -> Column:
        few = F.flatten(F.transform(f"{name}_packed", lambda x: F.array(*(F.shiftright(x, at).bitwiseAND(F.lit(_LOW21)) for at in (0, 21, 42)))))
        many = F.concat(*(apart(f"{name}_{seed}") for seed in SEEDS))
        return F.when(F.size(f"{name}_units") < APART, few).otherwise(F.transform(many, lambda x: x.bitwiseAND(F.lit(_LOW32))))

    kept = df.columns
    df = df.select("*", *(units_of(F.col(text)).alias(f"{name}_units") for name, text in texts.items()))
    df = df.select("*", *(F.transform(f"{name}_units", lambda u: F.xxhash64(u, F.lit(seed))).alias(f"{name}_{seed}") for name in texts for seed in SEEDS))
    df = df.select("*", *(F.when(F.size(f"{name}_units") < APART, F.array(*(packed(f"{name}_{seed}", at) for seed in SEEDS for at in range(SHIFTS)))).alias(f"{name}_packed") for name in texts))
    return df.select(*kept, *(F.concat(F.array(F.size(f"{name}_units").cast("bigint"), *(dense(name, k) for k in range(DENSE))), counts(name)).alias(name) for name in texts))


def combine(left: Column, right: Column, sign: int = 1) -> Column:
    """Lanes of the union (sign 1) or of the difference (sign -1) of two multisets."""
    pairs = F.zip_with(left, right, lambda a, b: a + sign * b)
    return F.transform(pairs, lambda x, i: F.when(i == 0, x).when(i <= DENSE, x.bitwiseAND(F.lit(_LOW60))).otherwise(x.bitwiseAND(F.lit(_LOW32))))


def rendered(lanes: Column) -> Column:
    """Hexadecimal text: 16 digits for the number of units and each dense lane, 8 for each count."""
    return F.array_join(F.transform(lanes, lambda x, i: F.lower(F.lpad(F.hex(x), F.when(i <= DENSE, 16).otherwise(8), F.lit("0")))), "")


def signed(lanes: Column) -> Column:
    """Counting lanes as sums of +1 and -1."""
    return F.transform(F.slice(lanes, DENSE + 2, 3 * SHIFTS * len(SEEDS)), lambda x: 2 * x - F.get(lanes, F.lit(0)))


def likeness(a: Column, b: Column) -> Column:
    """Estimated cosine of two lane arrays, 1 for equal fingerprints."""
    x, y = signed(a), signed(b)
    dot = F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    square = lambda v: F.aggregate(v, F.lit(0.0), lambda s, p: s + p * p)
    size = F.sqrt(square(x) * square(y))
    return F.when(a == b, 1.0).when(size == 0, 0.0).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), dot / size)))


def fingerprints(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, lanes, fingerprint) for every row."""
    made = with_lanes(df.select(F.col(key).alias("k"), F.col(text).alias("t")), lanes="t")
    return made.select(F.col("k").alias(key), "lanes", rendered(F.col("lanes")).alias("fingerprint"))


def following(ids: DataFrame) -> DataFrame:
    """(id, next_id): the next lower id, the highest after the lowest.  Ids are unique and not null."""
    top = ids.agg(F.max("id").alias("top"))
    return neighbours(ids, "id", "below").crossJoin(F.broadcast(top)).select("id", F.coalesce("below", "top").alias("next_id"))


def op8_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edit_report(table(spark, sf_dir, "documents"))


def edit_report(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Fingerprint of each text, of its edited form, and their likenesses, for every row.

    The edited text drops the last third and takes as many code points from the start of the next
    document (descending key; the highest follows the lowest).  Rows that repeat a key are one place in
    that order, held by their least text; a row with a null key has no next document, so its last
    third is dropped and its likeness to the next is 0.

    Texts are shuffled once, by key, with their lanes; both joins share that exchange.
    """
    docs = df.select(F.col(key).cast("bigint").alias("id"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    base = with_lanes(docs, lanes="t")
    counts = docs.where("id is not null").select("id", F.floor(F.length("t") / 3).cast("int").alias("third")).groupBy("id").agg(F.count("*").alias("n"), F.max("third").alias("most"))
    counts = cut_lineage(counts)
    wanted = following(counts.select("id")).join(counts, "id").select(F.col("id").alias("for_id"), "next_id", "most")
    keyed = base.where("id is not null")
    if counts.where("n > 1").limit(1).count():
        least = docs.where("id is not null").groupBy("id").agg(F.min("t").alias("t"))
        source = with_lanes(least, lanes="t")
    else:
        source = keyed
    heads = source.join(wanted, F.col("id") == F.col("next_id")).select("for_id", F.expr("substring(t, 1, most)").alias("head"), F.col("lanes").alias("next_lanes"))
    joined = keyed.join(heads, F.col("id") == F.col("for_id")).select("id", "t", "lanes", "head", "next_lanes")
    joined = joined.unionByName(base.where("id is null").select("id", "t", "lanes", F.lit("").alias("head"), F.lit(None).cast("array<bigint>").alias("next_lanes")))
    sized = joined.select("*", F.length("t").alias("n"), F.floor(F.length("t") / 3).cast("int").alias("third"))
    edited = F.when(F.col("third") > 0, F.concat(F.expr("substring(t, 1, n - third)"), F.expr("substring(head, 1, third)"))).otherwise(F.col("t"))
    ready = with_lanes(sized.select("id", "n", "lanes", "next_lanes", edited.alias("edited")), edited_lanes="edited")
    return ready.select(
        F.col("id").alias(key), F.col("n").cast("bigint").alias("n_chars"), F.sha2(F.col("edited"), 256).alias("edited_sha256"), rendered(F.col("lanes")).alias("fingerprint"), rendered(F.col("edited_lanes")).alias("edited_fingerprint"),
        F.round(likeness(F.col("lanes"), F.col("edited_lanes")), 6).alias("near_edited"), F.round(F.coalesce(likeness(F.col("lanes"), F.col("next_lanes")), F.lit(0.0)), 6).alias("near_next"),
    )
