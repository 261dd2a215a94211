"""Tables as items, dates, links and features, and readers for other formats."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import NOT_LETTER, WHITE, normalise_value, words
from ..operators.scan import ranged

#: Fixed value: licence names looked for in documents.
LICENCES = "(MIT License|Apache License|GNU General Public License|CC BY-NC)"
FEATURE_COLUMNS = ["item_id", "axis", "kind", "direction", "v_num", "v_txt"]


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_items(spark: SparkSession, path: str, fmt: str = "parquet", schema=None, **options) -> DataFrame:
    """Items from parquet, csv, json, orc or text."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def items_from(df: DataFrame, item_id: str, body: str, pub_date: str | None = None, year: str | None = None, **more: str) -> DataFrame:
    """Any document set as items; a missing date falls back to the first day of the year, an item with neither is left out."""
    day = F.col(pub_date).cast("date") if pub_date else F.lit(None).cast("date")
    if year:
        day = F.coalesce(day, F.make_date(F.col(year).cast("int"), F.lit(1), F.lit(1)))
    picked = df.select(F.col(item_id).cast("bigint").alias("item_id"), F.col(body).alias("body"), day.alias("pub_date"), *(F.col(c).alias(n) for n, c in more.items()))
    return picked.where("pub_date is not null").withColumn("year", F.year("pub_date"))


def document_items(docs: DataFrame) -> DataFrame:
    """Documents dated by id over 35 years: item_id, pub_date, year, lang, source and the body."""
    n = docs.agg(F.count("*").alias("n_docs"))
    day = F.date_add(F.lit("1990-01-01").cast("date"), F.floor(F.col("doc_id") * 12775 / F.col("n_docs")).cast("int"))
    return docs.crossJoin(F.broadcast(n)).select(F.col("doc_id").alias("item_id"), day.alias("pub_date"), F.year(day).alias("year"), "lang", "source", F.col("text").alias("body"))


def chain_links(rows: DataFrame, group: list[str], order: list[str], member: str) -> DataFrame:
    """(src, dst, relevance): in every group each member cites the member just before it and the first one.

    From distinct rows(group, order, member).  Relevance counts groups.  Links are at most two a row however large a group is:
    rows are put in order by ranges, so a group that is a third of the table is spread over many tasks.
    """
    columns = list(dict.fromkeys([*group, *order, member]))
    placed = ranged(rows.select(*columns), *group, *order)
    here = F.struct(*group, F.col(member).alias("m"))
    ends = placed.groupBy("range_").agg(F.max_by(here, "place_").alias("last"))
    carried = F.broadcast(ends.select("range_", F.lag("last").over(Window.orderBy("range_")).alias("carried")))  # a row for each range
    ahead = F.coalesce(F.lag(here).over(Window.partitionBy("range_").orderBy("place_")), F.col("carried"))
    chained = placed.join(carried, "range_").withColumn("ahead", ahead)
    same = F.lit(True)
    for g in group:
        same = same & F.col(f"ahead.{g}").eqNullSafe(F.col(g))
    first = rows.groupBy(*group).agg(F.min_by(member, F.struct(*order)).alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
    cited = F.array_distinct(F.array(F.col("ahead.m"), F.col("first")))
    return chained.where(same).join(first, group).select(F.col(member).alias("src"), F.explode(cited).alias("dst")).groupBy("src", "dst").agg(F.count("*").cast("double").alias("relevance"))


def document_links(docs: DataFrame, least: int = 40) -> DataFrame:
    """For each distinct line of `least` characters or more, a document cites the document before it that has the line and the
    first that had it.  Lines travel as two hashes."""
    lines = docs.select(F.col("doc_id"), F.explode(F.array_distinct(F.filter(F.transform(F.split("text", "\n"), F.trim), lambda x: F.length(x) >= least))).alias("line")).select("doc_id", F.xxhash64("line").alias("h0"), F.xxhash64("line", F.lit(1)).alias("h1")).distinct()
    return chain_links(lines, ["h0", "h1"], ["doc_id"], "doc_id")


def long_features(wide: DataFrame, numeric: dict[str, int], categorical: list[str], key: str = "item_id") -> DataFrame:
    """One row per item and axis from wide feature columns; numeric maps a column to its direction."""
    rows = [F.struct(F.lit(c).alias("axis"), F.lit("numeric").alias("kind"), F.lit(d).alias("direction"), F.col(c).cast("double").alias("v_num"), F.lit(None).cast("string").alias("v_txt")) for c, d in numeric.items()]
    rows += [F.struct(F.lit(c).alias("axis"), F.lit("categorical").alias("kind"), F.lit(1).alias("direction"), F.lit(None).cast("double").alias("v_num"), F.nullif(normalise_value(F.col(c)), F.lit("")).alias("v_txt")) for c in categorical]
    return wide.select(F.col(key).alias("item_id"), F.explode(F.array(*rows)).alias("x")).select("item_id", "x.*").where("v_num is not null or v_txt is not null")


DOCUMENT_NUMERIC = {"n_chars": 1, "n_words": 1, "diversity": 1, "word_length": 1, "n_lines": 1, "punct_share": -1}
DOCUMENT_CATEGORICAL = ["lang", "source", "licence", "lead_term", "opening"]


def document_features_wide(docs: DataFrame) -> DataFrame:
    """Features of each document, computed once per document however many targets it serves."""
    text = F.col("text")
    base = docs.select(
        F.col("doc_id").alias("item_id"), "lang", "source", F.length(text).cast("bigint").alias("n_chars"), F.size(words(text)).cast("bigint").alias("n_words"),
        F.size(F.array_distinct(words(F.lower(text)))).cast("bigint").alias("n_distinct"), F.length(F.regexp_replace(text, WHITE, "")).cast("bigint").alias("n_solid"),
        F.size(F.split(text, "\n")).cast("bigint").alias("n_lines"), (F.length(text) - F.length(F.regexp_replace(text, r"[!-/:-@\[-`{-~]", ""))).cast("bigint").alias("n_punct"),
        F.nullif(F.regexp_extract(text, LICENCES, 1), F.lit("")).alias("licence"),
        F.element_at(F.array_sort(F.transform(F.split(F.lower(text), NOT_LETTER), lambda w: F.struct((-F.length(w)).alias("n"), w.alias("w")))), 1)["w"].alias("lead_term"),
        F.substring(F.element_at(F.split(text, "\n"), 1), 1, 40).alias("opening"),
    )
    ratio = lambda a, b: F.round(F.try_divide(F.col(a).cast("double"), F.col(b)), 6)
    return base.select("item_id", "lang", "source", "licence", "lead_term", "opening", "n_chars", "n_words", "n_lines", ratio("n_distinct", "n_words").alias("diversity"), ratio("n_solid", "n_words").alias("word_length"), ratio("n_punct", "n_chars").alias("punct_share"))


def document_features(docs: DataFrame) -> DataFrame:
    return long_features(document_features_wide(docs), DOCUMENT_NUMERIC, DOCUMENT_CATEGORICAL)


PART_NUMERIC = {"price": -1, "size": 1, "discount": 1, "quantity": 1, "suppliers": 1, "return_share": -1}
PART_CATEGORICAL = ["brand", "type", "adjective", "noun", "nation"]


def part_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts with their first ship date and wide features."""
    lines = load(spark, sf_dir, "lineitem")
    per = lines.groupBy("l_partkey").agg(F.min(F.to_date("l_shipdate")).alias("pub_date"), F.count("*").alias("n_lines"), F.sum(F.round(F.col("l_discount") * 100).cast("bigint")).alias("discount_sum"), F.sum(F.col("l_quantity").cast("bigint")).alias("quantity"), F.count_distinct("l_suppkey").alias("suppliers"), F.sum(F.when(F.col("l_returnflag") == "R", 1).otherwise(0)).alias("returned"))
    nations = lines.select("l_partkey", "l_suppkey").join(load(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey")).join(F.broadcast(load(spark, sf_dir, "nation").select("n_nationkey", "n_name")), F.col("s_nationkey") == F.col("n_nationkey")).groupBy("l_partkey", "n_name").agg(F.count("*").alias("n")).groupBy("l_partkey").agg(F.min(F.struct((-F.col("n")).alias("n"), "n_name"))["n_name"].alias("nation"))
    name = F.split("p_name", " ")
    return load(spark, sf_dir, "part").join(per, F.col("p_partkey") == F.col("l_partkey")).join(nations, "l_partkey").select(
        F.col("p_partkey").alias("item_id"), "pub_date", F.year("pub_date").alias("year"), "n_lines", F.col("p_retailprice").alias("price"), F.col("p_size").alias("size"),
        F.round(F.col("discount_sum") / F.col("n_lines"), 6).alias("discount"), "quantity", "suppliers", F.round(F.col("returned") / F.col("n_lines"), 6).alias("return_share"),
        F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), F.element_at(name, 1).alias("adjective"), F.element_at(name, -1).alias("noun"), "nation",
    )


def part_links(spark: SparkSession, sf_dir: str, items: DataFrame) -> DataFrame:
    """In each order a part cites the part before it (by first ship date, then key) and the first one; relevance counts orders."""
    dated = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct().join(items.select(F.col("item_id").alias("l_partkey"), "pub_date"), "l_partkey")
    return chain_links(dated, ["l_orderkey"], ["pub_date", "l_partkey"], "l_partkey")


def line_series(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """Order lines as dated series by part, brand or supplier, with a total order."""
    lines = load(spark, sf_dir, "lineitem")
    if key == "p_brand":
        lines = lines.join(load(spark, sf_dir, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    order = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"]
    price = F.col("l_extendedprice") / F.col("l_quantity")
    numbered = Window.partitionBy("series").orderBy(*order)
    return lines.withColumn("series", F.col(key).cast("string")).select("series", F.row_number().over(numbered).cast("bigint").alias("pos"), price.alias("unit_price"), "l_discount", "l_quantity", "l_suppkey", "l_returnflag", "l_orderkey")


def page_items(pages: DataFrame) -> DataFrame:
    return pages.select(F.col("page_id").alias("item_id"), F.nullif(F.regexp_extract("url", r"^https?://([^/:?#]+)", 1), F.lit("")).alias("host"), F.nullif(F.regexp_extract("html", r"<title>([^<]*)</title>", 1), F.lit("")).alias("title"), F.size(F.split("html", "<a ")).cast("bigint").alias("link_pieces"), F.length("html").cast("bigint").alias("n_chars"))


def contained_passages(docs: DataFrame, passages: DataFrame, most: int = 2000, anchor: int = 5) -> DataFrame:
    """(item_id, passage_id) where a document holds a whole passage.

    Up to `most` passages are broadcast; more meet the documents by a shuffle on the same hashes.  Documents are screened by one hash per word: a passage can only occur where
    the hash of its second to sixth word occurs; passages too short for that are looked for everywhere.
    """
    n = passages.count()
    grams = lambda w: F.transform(F.sequence(F.lit(1), F.size(w) - (anchor - 1)), lambda i: F.xxhash64(F.array_join(F.slice(w, i, anchor), " ")))
    own = passages.select(F.col("item_id").alias("passage_id"), F.col("text").alias("passage"), words(F.col("text")).alias("w"))
    anchored = own.withColumn("h", F.when(F.size("w") >= anchor + 2, F.xxhash64(F.array_join(F.slice("w", 2, anchor), " "))))
    w = words(F.col("text"))
    if n > most:
        texts = docs.select(F.col("doc_id").alias("item_id"), "text")
        found = docs.select(F.col("doc_id").alias("item_id"), w.alias("w")).where(F.size("w") >= anchor).select("item_id", F.explode(F.array_distinct(grams(F.col("w")))).alias("h"))
        likely = found.join(anchored.where("h is not null").select("h", "passage_id", "passage"), "h").select(F.col("item_id").alias("at"), "passage_id", "passage").distinct()
        by_anchor = likely.join(texts, F.col("at").eqNullSafe(F.col("item_id"))).where(F.contains("text", "passage")).select("item_id", "passage_id")
        blocks = anchored.where("h is null").select("passage_id", "passage").repartition(-(-n // most), "passage_id").hint("shuffle_replicate_nl")
        return by_anchor.union(texts.join(blocks, F.contains("text", "passage")).select("item_id", "passage_id")).distinct()
    screen = anchored.agg(F.collect_set("h").alias("hs"))
    seen = docs.select(F.col("doc_id").alias("item_id"), "text", w.alias("w")).crossJoin(F.broadcast(screen)).select("item_id", "text", F.when(F.size("w") >= anchor, F.array_intersect(grams(F.col("w")), F.col("hs"))).otherwise(F.array().cast("array<bigint>")).alias("hit"))
    by_anchor = seen.where(F.size("hit") > 0).select("item_id", "text", F.explode("hit").alias("h")).join(F.broadcast(anchored.where("h is not null").select("h", "passage_id", "passage")), "h").where(F.contains("text", "passage")).select("item_id", "passage_id")
    short = seen.join(F.broadcast(anchored.where("h is null").select("passage_id", "passage")), F.contains("text", "passage")).select("item_id", "passage_id")
    return by_anchor.union(short).distinct()


def conversation_items(conversations: DataFrame) -> DataFrame:
    return conversations.select("conv_id", "turn", "role", F.length("text").cast("bigint").alias("n_chars"), F.size(F.array_distinct(words(F.lower("text")))).cast("bigint").alias("n_distinct"), F.lower(F.element_at(words(F.col("text")), 1)).alias("opening"))


def key_column(*parts: str) -> Column:
    return F.concat_ws("|", *parts)
