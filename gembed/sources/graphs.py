"""Graphs over the given tables, as (rel, src, dst, weight) with string keys: one select or aggregate a relation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..session import is_small, key_bytes, stored
from .tables import table

#: Runs of other characters than letters separate words.
NOT_LETTERS = r"[^\p{L}]+"
EVENT_TYPES = ("click", "view", "purchase", "signup", "error")


def tokens(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), NOT_LETTERS), lambda w: w != "")


def word_pairs(docs: DataFrame) -> DataFrame:
    """(src, dst) of each two consecutive words; the array is zipped with its own tail, no window."""
    return pairs_of(docs.select(tokens(F.col("text")).alias("w")))


def pairs_of(words: DataFrame) -> DataFrame:
    """The pairs of texts that are split already (w)."""
    words = words.where(F.size("w") > 1)
    pairs = F.arrays_zip(F.slice("w", F.lit(1), F.size("w") - 1).alias("src"), F.slice("w", F.lit(2), F.size("w") - 1).alias("dst"))
    return words.select(F.inline(pairs))


def word_next(spark: SparkSession, sf_dir: str, min_count: int = 10) -> DataFrame:
    """word -follows-> word, weight = occurrences; words with at least ``min_count`` ends of pairs.

    Words are counted in the texts, where a word ends two pairs, or one at either end of a text. If the frequent ones
    are few enough for every task, pairs with other words go before anything is shuffled.
    """
    held = stored(table(spark, sf_dir, "documents").select(tokens(F.col("text")).alias("w")), "words")  # else each use of an array would split the text anew
    words = held.where(F.size("w") > 1).select(F.size("w").alias("size"), F.posexplode("w").alias("pos", "word"))
    ends = words.groupBy("word").agg(F.sum((F.col("pos") > 0).cast("int") + (F.col("pos") < F.col("size") - 1).cast("int")).alias("n"))
    often = stored(ends.where(F.col("n") >= min_count).select("word"), "often")
    counted = lambda pairs: pairs.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight"))
    small = is_small(*key_bytes(often, "word"))
    kept = pairs_of(held) if small else counted(pairs_of(held))
    for end in ("src", "dst"):
        these = often.withColumnRenamed("word", end)
        kept = kept.join(F.broadcast(these) if small else these, end, "left_semi")
    return (counted(kept) if small else kept).select(F.lit("follows").alias("rel"), "src", "dst", "weight")


def doc_word(spark: SparkSession, sf_dir: str, min_docs: int = 1) -> DataFrame:
    """document -contains-> word, weight = count in the document."""
    words = table(spark, sf_dir, "documents").select("doc_id", F.explode(tokens(F.col("text"))).alias("dst"))
    edges = words.groupBy("doc_id", "dst").agg(F.count(F.lit(1)).alias("weight"))
    if min_docs > 1:
        edges = edges.join(edges.groupBy("dst").count().where(F.col("count") >= min_docs), "dst", "left_semi")
    return edges.select(F.lit("contains").alias("rel"), F.col("doc_id").cast("string").alias("src"), "dst", "weight")


def _rel(df: DataFrame, rel: str, src: str, dst: str, src_type: str, dst_type: str, weight: Column | None = None, distinct: bool = False) -> DataFrame:
    out = df.select(F.lit(rel).alias("rel"), F.concat(F.lit(f"{src_type}:"), F.expr(src).cast("string")).alias("src"), F.concat(F.lit(f"{dst_type}:"), F.expr(dst).cast("string")).alias("dst"))
    if distinct:
        return out.groupBy("rel", "src", "dst").agg(F.count(F.lit(1)).alias("weight"))
    return out.withColumn("weight", F.lit(1).cast("long"))


def kb(spark: SparkSession, sf_dir: str, add_inverse: bool = False) -> DataFrame:
    """A knowledge base of many relations over the star schema and the events; keys carry their type."""
    t = lambda name: table(spark, sf_dir, name)
    part, customer = t("part"), t("customer")
    parts = [
        _rel(customer, "customer_in_nation", "c_custkey", "c_nationkey", "customer", "nation"),
        _rel(t("supplier"), "supplier_in_nation", "s_suppkey", "s_nationkey", "supplier", "nation"),
        _rel(t("nation"), "nation_in_region", "n_nationkey", "n_regionkey", "nation", "region"),
        _rel(part, "part_brand", "p_partkey", "p_brand", "part", "brand"),
        _rel(part, "part_type", "p_partkey", "p_type", "part", "type"),
        _rel(part, "part_size", "p_partkey", "p_size", "part", "size"),
        _rel(customer, "customer_segment", "c_custkey", "c_mktsegment", "customer", "segment"),
        _rel(t("orders"), "order_by_customer", "o_orderkey", "o_custkey", "order", "customer"),
        _rel(t("orders"), "order_priority", "o_orderkey", "o_orderpriority", "order", "priority"),
        _rel(t("lineitem"), "order_has_part", "l_orderkey", "l_partkey", "order", "part", distinct=True),
        _rel(t("lineitem"), "part_from_supplier", "l_partkey", "l_suppkey", "part", "supplier", distinct=True),
    ]
    events = t("events").where(F.col("event_type").isin(*EVENT_TYPES))
    each = events.select(F.concat(F.lit("user_"), "event_type").alias("rel"), F.concat(F.lit("user:"), "user_id").alias("src"), F.concat(F.lit("hour:"), F.hour("ts")).alias("dst"))
    parts.append(each.groupBy("rel", "src", "dst").agg(F.count(F.lit(1)).alias("weight")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    if add_inverse:
        out = out.unionByName(out.select(F.concat("rel", F.lit("_inverse")).alias("rel"), F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    return out


def inverse_relations(edges: DataFrame, threshold: float = 0.95) -> DataFrame:
    """(rel, of, share): relations whose pairs, swapped, are mostly those of an earlier relation."""
    size = edges.groupBy("rel").agg(F.count(F.lit(1)).alias("n"))
    swapped = edges.select(F.col("rel").alias("of"), F.col("src").alias("_d"), F.col("dst").alias("_s"))
    common = edges.join(swapped, (edges["src"] == swapped["_s"]) & (edges["dst"] == swapped["_d"]) & (edges["rel"] > swapped["of"])).groupBy("rel", "of").agg(F.count(F.lit(1)).alias("common"))
    return common.join(size, "rel").select("rel", "of", (F.col("common") / F.col("n")).alias("share")).where(F.col("share") >= threshold)


def remove_inverse(edges: DataFrame, threshold: float = 0.95) -> DataFrame:
    return edges.join(F.broadcast(inverse_relations(edges, threshold).select("rel").distinct()), "rel", "left_anti")


def purchases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """customer -buys-> part, weight = order lines."""
    lines, orders = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    joined = lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"])
    return joined.groupBy(F.col("o_custkey").cast("string").alias("src"), F.col("l_partkey").cast("string").alias("dst")).agg(F.count(F.lit(1)).alias("weight")).select(F.lit("buys").alias("rel"), "src", "dst", "weight")


def user_event(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy(F.col("user_id").cast("string").alias("src"), F.col("event_type").alias("dst")).agg(F.count(F.lit(1)).alias("weight")).select(F.lit("did").alias("rel"), "src", "dst", "weight")


def placed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """order -placed_by-> customer."""
    return table(spark, sf_dir, "orders").select(F.lit("placed_by").alias("rel"), F.col("o_orderkey").cast("string").alias("src"), F.col("o_custkey").cast("string").alias("dst"), F.lit(1).cast("long").alias("weight"))


def knn(spark: SparkSession, sf_dir: str, k: int = 5) -> DataFrame:
    """vector -near-> its k best others by dot product, ties by id; exact, by blocks (operators.nearest)."""
    from ..operators.nearest import nearest_exact

    vectors = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    best = nearest_exact(vectors, vectors, k, drop_self=True)
    return best.select(F.lit("near").alias("rel"), F.col("query").cast("string").alias("src"), F.col("id").cast("string").alias("dst"), F.lit(1).cast("long").alias("weight"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page -links-> token of an href, page -hosted_by-> host of its url."""
    pages = table(spark, sf_dir, "pages")
    hrefs = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'href="/([^"]*)"'), F.lit(1))).alias("dst"))
    links = hrefs.groupBy("page_id", "dst").agg(F.count(F.lit(1)).alias("weight")).select(F.lit("links").alias("rel"), F.col("page_id").cast("string").alias("src"), "dst", "weight")
    hosts = pages.select(F.lit("hosted_by").alias("rel"), F.col("page_id").cast("string").alias("src"), F.regexp_extract("url", r"^[a-z]+://([^/?#:]+)", 1).alias("dst"), F.lit(1).cast("long").alias("weight"))
    return links.unionByName(hosts)


def conv_word(spark: SparkSession, sf_dir: str) -> DataFrame:
    """conversation -role-> word, one relation per role."""
    words = table(spark, sf_dir, "conversations").select("role", "conv_id", F.explode(tokens(F.col("text"))).alias("dst"))
    return words.groupBy(F.col("role").alias("rel"), F.col("conv_id").cast("string").alias("src"), "dst").agg(F.count(F.lit(1)).alias("weight"))


def bigrams_by_window(docs: DataFrame) -> DataFrame:
    """The same pairs as ``word_pairs`` by lead over positions: the costlier form, kept as its check."""
    each = docs.select("doc_id", F.posexplode(tokens(F.col("text"))).alias("pos", "src"))
    after = F.lead("src").over(Window.partitionBy("doc_id").orderBy("pos"))
    return each.withColumn("dst", after).where("dst is not null").select("src", "dst")
