"""Operator 7: benchmark decontamination through a positional inverted index, in DataFrame functions alone.

Of each benchmark window the two terms that are rarest in the corpus are its anchors. The index stores the postings of
all anchors: term, document, position and the words around it. A window's lists are brought to its start (position
less offset) and intersected; the words around the anchor then decide whether the phrase stands there exactly. Texts
are never shuffled: postings are made while reading, and only of anchors.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from packvec.llm.common import LOWER, UPPER, written

WINDOW = 13
#: Rows of a term table that is broadcast at most (about 100 bytes each); a longer one is joined by a shuffle.
MAX_BROADCAST_TERMS = 500_000
SEPARATORS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def lowered(text: Column) -> Column:
    """A-Z as a-z, other letters as they are. lower() does just that to ASCII texts, and faster."""
    return F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def words_of(text: Column) -> Column:
    """Words [^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+ of the lower-cased text; none for null."""
    return F.coalesce(F.array_remove(F.split(lowered(text), SEPARATORS), ""), F.array().cast("array<string>"))


def keyed(df: DataFrame, id: str, text: str) -> DataFrame:
    """_id, _key, _text: a row is known by its id and a hash of its text, so ids may repeat or be null."""
    return df.select(F.col(id).alias("_id"), F.xxhash64(F.col(id).cast("string"), F.col(text)).alias("_key"), F.col(text).alias("_text"))


def bounded(df: DataFrame) -> DataFrame:
    """df (a written table), to be broadcast if its counted rows are within MAX_BROADCAST_TERMS."""
    return F.broadcast(df) if df.count() <= MAX_BROADCAST_TERMS else df


def windows_of(items: DataFrame, item_id: str, text: str, n: int) -> DataFrame:
    """phrase, len, terms (array), item: each n words of each item, or all words of a shorter one."""
    words = items.select(F.col(item_id).cast("string").alias("item"), words_of(F.col(text)).alias("w")).where(F.size("w") > 0)
    starts = words.select("item", "w", F.least(F.size("w"), F.lit(n)).alias("len")).select("item", "w", "len", F.explode(F.sequence(F.lit(1), F.size("w") - F.col("len") + 1)).alias("at"))
    cut = starts.select("item", "len", F.slice("w", F.col("at"), F.col("len")).alias("terms"))
    return cut.select("item", "len", "terms", F.array_join("terms", " ").alias("phrase")).distinct()


def term_counts(docs: DataFrame, terms: DataFrame, text: str = "_text") -> DataFrame:
    """Occurrences in the corpus of each of terms (column term)."""
    return docs.select(F.explode(words_of(F.col(text))).alias("term")).join(terms, "term").groupBy("term").agg(F.count(F.lit(1)).alias("n"))


def anchors_of(windows: DataFrame, counts: DataFrame) -> DataFrame:
    """phrase, len, term, offset (from 0), slots, slot: the one or two rarest terms of each window that the corpus has.

    Windows with a term that the corpus lacks cannot occur and have none.
    """
    phrases = windows.select("phrase", "len", "terms").distinct()
    at = phrases.select("phrase", "len", F.posexplode("terms").alias("offset", "term")).groupBy("phrase", "len", "term").agg(F.min("offset").alias("offset"))
    known = at.join(counts, "term", "left")
    order = Window.partitionBy("phrase").orderBy("n", "term")
    whole = Window.partitionBy("phrase")
    ranked = known.withColumns({"slot": F.row_number().over(order), "absent": F.count_if(F.col("n").isNull()).over(whole), "slots": F.least(F.count(F.lit(1)).over(whole), F.lit(2))})
    return ranked.where((F.col("absent") == 0) & (F.col("slot") <= 2)).select("phrase", "len", "term", "offset", "slot", "slots")


def build_index(docs: DataFrame, terms: DataFrame, reach: int = WINDOW - 1) -> DataFrame:
    """Postings of terms: term, _id, _key, pos (from 0), from (position of around's first word), around (words up to reach away)."""
    words = docs.select("_id", "_key", words_of(F.col("_text")).alias("w"))
    each = words.select("_id", "_key", "w", F.posexplode("w").alias("pos", "term")).join(terms, "term")
    first = F.greatest(F.col("pos") - reach, F.lit(0))
    return each.select("term", "_id", "_key", "pos", first.alias("from"), F.slice("w", first + 1, F.col("pos") + reach + 1 - first).alias("around"))


def phrases_in(index: DataFrame, anchors: DataFrame) -> DataFrame:
    """_id, _key, phrase, start, len of all exact occurrences: offset-adjusted lists intersected, then compared word by word."""
    start = (F.col("pos") - F.col("offset")).alias("start")
    lists = index.join(anchors, "term").select("_id", "_key", "phrase", "len", "slot", "slots", start, "from", "around").where(F.col("start") >= 0)
    there = (F.col("start") >= F.col("from")) & (F.array_join(F.slice("around", F.greatest(F.col("start") - F.col("from"), F.lit(0)) + 1, F.col("len")), " ") == F.col("phrase"))
    held = lists.where(there).select("_id", "_key", "phrase", "len", "start", "slots", "slot")
    met = held.groupBy("_id", "_key", "phrase", "len", "start").agg(F.bit_or(F.col("slot").cast("int")).alias("slots_met"), F.max("slots").alias("slots"))
    return met.where((F.col("slots_met") == F.when(F.col("slots") == 2, 3).otherwise(1))).select("_id", "_key", "phrase", "start", "len")


def proximity(index: DataFrame, terms: Sequence[str], within: int) -> DataFrame:
    """_id, _key, start, end of places where all terms stand within so many words, from the first term's postings on."""
    out = index.where(F.col("term") == terms[0]).select("_id", "_key", F.col("pos").alias("start"), F.col("pos").alias("end"))
    for t in terms[1:]:
        other = index.where(F.col("term") == t).select(F.col("_id").alias("_i"), F.col("_key").alias("_k"), "pos")
        low, high = F.least("start", "pos"), F.greatest("end", "pos")
        out = out.join(other, out["_id"].eqNullSafe(other["_i"]) & (out["_key"] == other["_k"])).where(high - low < within).select("_id", "_key", low.alias("start"), high.alias("end")).distinct()
    return out


def covered(spans: Column) -> Column:
    """Positions in the union of (start, len) spans."""
    start = F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("n"))

    def step(a: Column, s: Column) -> Column:
        end = s["start"] + s["len"]
        new = F.greatest(end - F.greatest(a["end"], s["start"]), F.lit(0))
        return F.struct(F.greatest(a["end"], end).alias("end"), (a["n"] + new).alias("n"))

    return F.aggregate(F.array_sort(spans), start, step, lambda a: a["n"])


def contamination(docs: DataFrame, items: DataFrame, id: str = "doc_id", text: str = "text", item_id: str = "item_id", item_text: str = "text", n: int = WINDOW) -> DataFrame:
    """_id, _key, n_words, n_hit, n_items, items (sorted ids as strings), contaminated; one row for each row of docs.

    A document is contaminated if its words inside occurrences of benchmark windows are at least 1 in 20 of its words.
    Edge cases: null and empty texts have no words and no hits; items without words take no part; those with a null id
    hit, but are not counted or listed; repeated rows and items count once in the index and get results each; empty tables give no hits.
    """
    own = keyed(docs, id, text)
    windows = written(windows_of(items, item_id, item_text, n), "windows")
    vocabulary = written(windows.select(F.explode("terms").alias("term")).distinct(), "vocabulary")
    anchors = written(anchors_of(windows, term_counts(own, bounded(vocabulary))), "anchors")
    terms = written(anchors.select("term").distinct(), "terms")
    index = written(build_index(own, bounded(terms), n - 1), "postings")
    found = phrases_in(index, bounded(anchors)).join(windows.select("phrase", "item"), "phrase")
    by_doc = found.groupBy("_id", "_key").agg(F.collect_set(F.struct("start", "len")).alias("spans"), F.collect_set("item").alias("ids"))
    hits = by_doc.select(F.col("_id").alias("_i"), F.col("_key").alias("_k"), covered(F.col("spans")).alias("hit"), F.array_sort("ids").alias("ids"))
    sized = own.select("_id", "_key", F.coalesce(F.regexp_count("_text", F.lit(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")), F.lit(0)).cast("long").alias("n_words"))
    joined = sized.join(hits, sized["_id"].eqNullSafe(hits["_i"]) & (sized["_key"] == hits["_k"]), "left")
    n_hit, ids = F.coalesce("hit", F.lit(0)).cast("long"), F.coalesce("ids", F.array().cast("array<string>"))
    return joined.select("_id", "_key", "n_words", n_hit.alias("n_hit"), F.size(ids).cast("long").alias("n_items"), ids.alias("items"), ((n_hit > 0) & (n_hit * 20 >= F.col("n_words"))).alias("contaminated"))
