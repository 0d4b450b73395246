"""Benchmark decontamination through a distributed positional inverted index. DataFrame functions only.

A posting is (term, document, position). A phrase of the benchmark is looked up from its two rarest terms: their postings, shifted
by the terms' offsets in the phrase, have to agree on a start; the words at the agreed starts are then compared exactly. Only
terms that some phrase is looked up by are posted, so what is shuffled follows the rare terms, not the corpus.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import UPPER, pick, written

DELIMITERS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: A side is broadcast up to so many bytes, by its counted rows and the measured bytes of its texts; beyond, Spark shuffles both.
BROADCAST_BYTES = 64 << 20


def words(text: Column) -> Column:
    """Lower-cased (A-Z) words of a text; none for null. All-ASCII texts take the quicker lower()."""
    low = F.when(F.length(text) == F.octet_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, UPPER.lower()))
    return F.coalesce(F.filter(F.split(low, DELIMITERS), lambda w: w != ""), F.array().cast("array<string>"))


def small(table: DataFrame, row_bytes: int, rows: int | None = None, texts: tuple[str, ...] = ()) -> DataFrame:
    """`table` (a stored one) with a broadcast hint if its rows of `row_bytes` and the measured bytes of the columns `texts` fit the bound."""
    size = 0
    if rows is None:
        rows, size = table.agg(F.count("*"), F.coalesce(F.sum(F.octet_length(F.concat_ws("", *texts)) if texts else F.lit(0)), F.lit(0))).first()
    return F.broadcast(table) if rows * row_bytes + size <= BROADCAST_BYTES else table


def rows_of(docs: DataFrame) -> DataFrame:
    """(doc_id, th, text): rows equal in id and text hash are equal rows, so (doc_id, th) serves as their key."""
    return pick(docs, "doc_id", "text").select("doc_id", F.xxhash64("text").alias("th"), "text")


def postings(docs: DataFrame, terms: DataFrame | None = None) -> DataFrame:
    """The index: (term, doc_id, th, pos), positions from 0; restricted to the column `term` of `terms` if that is given."""
    index = rows_of(docs).select("doc_id", "th", F.posexplode(words(F.col("text"))).alias("pos", "term"))
    return index if terms is None else index.join(terms.select("term").distinct() if terms.columns != ["term"] else terms, "term", "left_semi")


def phrases_of(items: DataFrame, n: int) -> DataFrame:
    """Windows of n consecutive words (or all of fewer): (phrase, size, items), each distinct phrase once."""
    found = pick(items, "item_id", "text").select(F.coalesce(F.col("item_id").cast("string"), F.lit("null")).alias("item"), words(F.col("text")).alias("w")).where(F.size("w") > 0)
    return (
        found.select("item", F.explode(F.transform(F.sequence(F.lit(0), F.greatest(F.size("w") - n, F.lit(0))), lambda s: F.slice("w", s + 1, n))).alias("window"))
        .groupBy(F.array_join("window", " ").alias("phrase")).agg(F.collect_set("item").alias("items"))
        .select("phrase", F.size(F.split("phrase", " ")).alias("size"), "items")
    )


def phrase_matches(docs: DataFrame, phrases: DataFrame) -> DataFrame:
    """Exact matches (doc_id, th, start, size, items) of the phrases in whole texts, one row for each place."""
    known = written(phrases.withColumn("window", F.monotonically_increasing_id()))
    terms = known.select("window", "size", F.posexplode(F.split("phrase", " ")).alias("offset", "term"))
    vocabulary = written(terms.select("term").distinct())
    counts = postings(docs, small(vocabulary, 32, texts=("term",))).groupBy("term").agg(F.count("*").alias("n"))
    weighed = terms.join(counts, "term", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    # A phrase with a term that the corpus lacks can't occur.
    rarest = weighed.groupBy("window").agg(F.min("n").alias("least"), F.slice(F.array_sort(F.collect_list(F.struct("n", "offset", "term"))), 1, 2).alias("terms")).where("least > 0")
    anchors = written(rarest.select("window", F.size("terms").alias("need"), F.posexplode("terms").alias("k", "t")).select("window", "need", "k", "t.offset", "t.term"))
    anchor_terms = written(anchors.select("term").distinct())
    places = (
        postings(docs, small(anchor_terms, 32, texts=("term",))).join(small(anchors, 48, texts=("term",)), "term")
        .select("doc_id", "th", "window", (F.col("pos") - F.col("offset")).alias("start"), "need", F.expr("shiftleft(1, k)").alias("bit")).where("start >= 0")
        .groupBy("doc_id", "th", "window", "start", "need").agg(F.bit_or("bit").alias("met")).where("met = shiftleft(1, need) - 1")
    )
    by_doc = written(places.groupBy("doc_id", "th").agg(F.collect_list(F.struct("window", "start")).alias("places")))
    n, total = by_doc.agg(F.count("*"), F.coalesce(F.sum(F.size("places")), F.lit(0))).first()
    longest = known.agg(F.coalesce(F.max("size"), F.lit(1))).first()[0]
    found = small(by_doc, 1, rows=48 * n + 24 * total).select(F.col("doc_id").alias("d"), F.col("th").alias("h"), "places")
    seen = (
        rows_of(docs).join(found, F.expr("doc_id <=> d and th = h"))
        .select("doc_id", "th", words(F.col("text")).alias("w"), "places")
        .select("doc_id", "th", F.explode(F.expr(f"transform(places, p -> struct(p.window as window, p.start as start, slice(w, p.start + 1, {longest}) as words))")).alias("p"))
        .select("doc_id", "th", "p.*")
    )
    return seen.join(small(known, 64, texts=("phrase", "items")), "window").where(F.array_join(F.slice("words", 1, F.col("size")), " ") == F.col("phrase")).select("doc_id", "th", "start", "size", "items").distinct()


def proximity_matches(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """(doc_id, th, left, right, pos_left, pos_right): places where `right` stands at most `within` words after `left`; pairs: (left, right, within).

    Both posting lists meet by document and block of `within` positions, so no list is paired with itself as a whole."""
    asked = written(pairs.select("left", "right", "within"))
    ends = written(asked.select("right", "within").distinct())
    a = postings(docs, asked.select(F.col("left").alias("term")).distinct()).withColumnsRenamed({"term": "left", "pos": "pos_left"}).join(small(asked, 48, texts=("left", "right")), "left")
    b = postings(docs, asked.select(F.col("right").alias("term")).distinct()).withColumnsRenamed({"term": "right", "pos": "pos_right"})
    a = a.withColumn("block", F.explode(F.array(F.expr("pos_left div within"), F.expr("pos_left div within + 1"))))
    b = b.join(small(ends, 48, texts=("right",)), "right").withColumn("block", F.expr("pos_right div within"))
    b = b.select(F.col("doc_id").alias("d"), "th", "right", "within", "block", "pos_right")
    return a.join(b, [a.th == b.th, a.doc_id.eqNullSafe(b.d), a.right == b.right, a.within == b.within, a.block == b.block]).where((F.col("pos_right") > F.col("pos_left")) & (F.col("pos_right") - F.col("pos_left") <= a.within)).select("doc_id", a.th, a.left, a.right, "pos_left", "pos_right")


def contamination(docs: DataFrame, benchmark: DataFrame, n: int = 10) -> DataFrame:
    """(doc_id, n_words, n_hit, items, contaminated) of each row: words inside any occurrence of a window of n item words, and the ids of the items that occur.

    Items of fewer words than n (but not none) are one window. Null or empty texts have no words, on either side; a null item_id is
    called 'null'. Rows that share a doc_id but not the text are told apart; repeated rows come out as often as they go in. Empty
    tables: nothing is hit, or no rows. Further columns are ignored.
    """
    matches = phrase_matches(docs, phrases_of(benchmark, n))
    hits = matches.groupBy(F.col("doc_id").alias("d"), F.col("th").alias("h")).agg(
        F.size(F.array_distinct(F.flatten(F.collect_set(F.sequence("start", F.col("start") + F.col("size") - 1))))).cast("long").alias("n_hit"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"),
    )
    counted = rows_of(docs).select("doc_id", "th", F.size(words(F.col("text"))).cast("long").alias("n_words"))
    return counted.join(hits, F.expr("doc_id <=> d and th = h"), "left").select(
        "doc_id", "n_words", F.coalesce("n_hit", F.lit(0)).alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"), F.col("n_hit").isNotNull().alias("contaminated")
    )
