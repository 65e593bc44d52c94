"""Benchmark decontamination over a positional inverted index of the training words; DataFrame functions only.

Words are runs of digits, letters a-z (A-Z lower-cased) and any non-ASCII character. One pass over the texts stores the
postings (term, document, position) of all training words, besides one length posting per document. The index knows nothing
of the test set, so any other can be asked of it. It is sharded by document: a shard holds its documents' whole lists, and
terms are looked up by broadcast, so nothing but what a test term hits is ever shuffled.

A test phrase is matched from its rarest terms: the lists of the two rarest are shifted by the terms' offsets in the phrase
and intersected on (phrase, document, start); only in documents that are left the other terms' postings are fetched and have
to be there at their offsets. Proximity asks the same index: a query's rarest term anchors it, and the other terms' postings
are fetched by blocks of positions around the anchors.

Defined results: null texts have no words; an item of fewer words than the window is one window, an item without words none;
rows that share a doc_id are judged one by one; a null item_id takes part in windows but is not listed; other columns are
ignored. Test terms are broadcast behind a count (see plans.joins.lookup), as rows of one term and a few numbers, and joined
over salts beyond it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from labelflow.llm.common import ascii_lower, materialise, release
from labelflow.plans.joins import lookup

WIDTH = 10
GAPS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
#: Stands for a document's length posting; no word holds it.
LENGTH = "\x00"


def _lower_word(word: Column) -> Column:
    """Lower-case A-Z in a word: the fast way where it is plain ASCII."""
    return F.when(F.length(word) == F.octet_length(word), F.lower(word)).otherwise(ascii_lower(word))


def split_words(text: Column) -> Column:
    """Words of a text in their case; the first or last may be empty where the text begins or ends with a gap."""
    return F.split(F.coalesce(text, F.lit("")), GAPS)


def word_array(text: Column) -> Column:
    """Lower-cased words without empty ones; for the benchmark, which is small."""
    return F.filter(F.split(ascii_lower(F.coalesce(text, F.lit(""))), GAPS), lambda w: w != "")


def phrases_of(benchmark: DataFrame, width: int = WIDTH) -> tuple[DataFrame, DataFrame]:
    """(phrase_id, words) of the distinct windows of `width` item words, and (phrase_id, item_id) of the items they come from."""
    items = benchmark.select("item_id", word_array(F.col("text")).alias("all_words")).filter(F.size("all_words") > 0)
    starts = F.explode(F.sequence(F.lit(0), F.greatest(F.size("all_words") - width, F.lit(0))))
    each = items.select("item_id", "all_words", starts.alias("i")).select("item_id", F.slice("all_words", F.col("i") + 1, width).alias("words"))
    each = materialise(each.distinct(), "windows")
    phrases = materialise(each.select("words").distinct().select(F.monotonically_increasing_id().alias("phrase_id"), "words"), "phrases")
    return phrases, materialise(each.join(phrases, "words").select("phrase_id", "item_id"), "phrase-items")


def build_index(docs: DataFrame) -> DataFrame:
    """Stored postings (rid, doc_id, term, pos) of all words; rid numbers the input rows. The posting of a document's length
    has the term LENGTH, the length as pos, and alone names the doc_id."""
    held = F.concat(F.array(F.lit(LENGTH)), split_words(F.col("text")))
    rows = docs.select(F.monotonically_increasing_id().alias("rid"), F.col("doc_id").cast("long").alias("doc_id"), held.alias("held"))
    size = F.size("held") - 1
    n_words = size - (F.element_at("held", 2) == "").cast("int") - ((size > 1) & (F.element_at("held", -1) == "")).cast("int")
    each = rows.select("rid", "doc_id", n_words.alias("n_words"), F.posexplode("held").alias("at", "word")).filter("word != ''")
    is_length = F.col("at") == 0
    return materialise(each.select("rid", F.when(is_length, F.col("doc_id")).alias("doc_id"), _lower_word(F.col("word")).alias("term"), F.when(is_length, F.col("n_words")).otherwise(F.col("at")).alias("pos")), "index")


def ranked_terms(index: DataFrame, phrases: DataFrame) -> DataFrame:
    """(phrase_id, n_terms, term, offset, rank) of the phrases all of whose terms occur; rank 1 is the rarest."""
    each = phrases.select("phrase_id", F.size("words").alias("n_terms"), F.posexplode("words").alias("offset", "term"))
    terms = materialise(each.select("term").distinct(), "terms")
    counts = materialise(lookup(index.select("term"), terms, ["term"], "inner").groupBy("term").agg(F.count("*").alias("n")), "counts")
    found = each.join(counts, "term", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    one = Window.partitionBy("phrase_id")
    ranked = found.withColumn("least", F.min("n").over(one)).filter("least > 0").withColumn("rank", F.row_number().over(one.orderBy("n", "offset")))
    out = materialise(ranked.select("phrase_id", "n_terms", "term", "offset", "rank"), "ranked")
    release(terms, counts)
    return out


def _lists(index: DataFrame, terms: DataFrame) -> DataFrame:
    """The stored lists of some terms: (rid, term, pos)."""
    wanted = materialise(terms.select("term").distinct(), "terms")
    return lookup(index.select("rid", "term", "pos"), wanted, ["term"], "inner", "rid")


def phrase_matches(index: DataFrame, ranked: DataFrame) -> DataFrame:
    """(rid, start, length, phrase_id) of every place where a phrase occurs."""
    rare = materialise(_lists(index, ranked.filter("rank <= 2")), "rare")
    of_rank = lambda k: materialise(ranked.filter(F.col("rank") == k).select("term", "phrase_id", "n_terms", "offset"), "of-rank")
    shifted = lambda k: lookup(rare, of_rank(k), ["term"], "inner", "rid").select("phrase_id", "n_terms", "rid", (F.col("pos") - F.col("offset")).alias("start"))
    first = shifted(1)
    both = first.filter("n_terms > 1").join(shifted(2).drop("n_terms"), ["phrase_id", "rid", "start"]).select(*first.columns)
    left = materialise(both.unionByName(first.filter("n_terms = 1")), "candidates")
    rest = materialise(ranked.filter("rank > 2").select("phrase_id", "term", "offset"), "rest")
    where = materialise(left.filter("n_terms > 2").select("rid").distinct(), "where")
    lists = _lists(lookup(index, where, ["rid"], "inner", "pos"), rest)
    asked = lookup(left.filter("n_terms > 2"), rest, ["phrase_id"], "inner", "rid").withColumn("pos", F.col("start") + F.col("offset"))
    whole = asked.join(lists, ["rid", "pos", "term"]).groupBy("phrase_id", "n_terms", "rid", "start").agg(F.count("*").alias("there")).filter("there = n_terms - 2")
    out = left.filter("n_terms <= 2").unionByName(whole.select(*left.columns))
    out = materialise(out.select("rid", "start", F.col("n_terms").alias("length"), "phrase_id"), "matches")
    release(rare, left, rest, where)
    return out


def proximity_matches(index: DataFrame, queries: DataFrame, span: int = WIDTH) -> DataFrame:
    """(query_id, doc_id, n): places of a query's rarest term with all its other terms within `span` consecutive words.

    `queries` holds (query_id, text). Every occurrence of the rarest term that lies in such a run counts once."""
    wanted = queries.select("query_id", F.array_distinct(word_array(F.col("text"))).alias("words")).filter(F.size("words") > 0)
    wanted = materialise(wanted.select("query_id", "words", F.monotonically_increasing_id().alias("phrase_id")), "queries")
    ranked = ranked_terms(index, wanted.select("phrase_id", "words"))
    first = materialise(ranked.filter("rank = 1").select("term", "phrase_id", "n_terms"), "anchors")
    anchors = materialise(lookup(_lists(index, first), first, ["term"], "inner", "rid").select("phrase_id", "n_terms", "rid", F.col("pos").alias("anchor")), "anchored")
    block = lambda c: F.floor(F.col(c) / span).cast("int")
    rest = materialise(ranked.filter("rank > 1").select("phrase_id", "term"), "rest")
    where = materialise(anchors.filter("n_terms > 1").select("rid").distinct(), "where")
    lists = _lists(lookup(index, where, ["rid"], "inner", "pos"), rest).withColumn("block", block("pos"))
    asked = lookup(anchors.filter("n_terms > 1"), rest, ["phrase_id"], "inner", "rid")
    asked = asked.withColumn("block", F.explode(F.sequence(block("anchor") - 1, block("anchor") + 1)))
    near = asked.join(lists, ["rid", "term", "block"]).filter(F.abs(F.col("pos") - F.col("anchor")) < span)
    found = near.groupBy("phrase_id", "n_terms", "rid", "anchor").agg(F.collect_list(F.struct("pos", "term")).alias("around"))  # under 2 * span places
    run = lambda s: F.size(F.array_distinct(F.transform(F.filter("around", lambda x: (x["pos"] >= s) & (x["pos"] < s + span)), lambda x: x["term"]))) == F.col("n_terms") - 1
    found = found.filter(F.exists(F.sequence(F.col("anchor") - span + 1, F.col("anchor")), run)).select("phrase_id", "rid")
    hits = found.unionByName(anchors.filter("n_terms = 1").select("phrase_id", "rid"))
    names = index.filter(F.col("term") == LENGTH).select("rid", "doc_id")
    return hits.join(wanted.select("phrase_id", "query_id"), "phrase_id").join(names, "rid").groupBy("query_id", "doc_id").agg(F.count("*").alias("n"))


def covered_words(matches: DataFrame) -> DataFrame:
    """(rid, n_hit): words inside any match, each once."""
    spots = matches.groupBy("rid", "start").agg(F.max(F.col("start") + F.col("length")).alias("stop"))
    before = F.max("stop").over(Window.partitionBy("rid").orderBy("start").rowsBetween(Window.unboundedPreceding, -1))
    new = F.greatest(F.lit(0), F.col("stop") - F.greatest("start", F.coalesce(before, F.lit(0))))
    return spots.withColumn("new", new).groupBy("rid").agg(F.sum("new").cast("long").alias("n_hit"))


def decontaminate(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH) -> DataFrame:
    """One row per document: rid, doc_id, n_words, n_hit, n_items, items (sorted strings), items_sha256, contaminated."""
    index = build_index(docs)
    phrases, sources = phrases_of(benchmark, width)
    ranked = ranked_terms(index, phrases)
    matches = phrase_matches(index, ranked)
    found = lookup(matches.select("rid", "phrase_id").distinct(), sources, ["phrase_id"], "inner", "rid").select("rid", F.col("item_id").alias("item")).distinct()
    items = found.groupBy("rid").agg(F.array_sort(F.collect_list(F.col("item").cast("string"))).alias("items"))
    lengths = materialise(index.filter(F.col("term") == LENGTH).select("rid", "doc_id", F.col("pos").cast("long").alias("n_words")), "lengths")
    release(index, phrases, ranked)
    out = lengths.join(covered_words(matches), "rid", "left").join(items, "rid", "left")
    items = F.coalesce("items", F.array().cast("array<string>"))
    return out.select(
        "rid", "doc_id", "n_words",
        F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"),
        F.size(items).cast("long").alias("n_items"),
        items.alias("items"),
        F.sha2(F.concat_ws(",", items), 256).alias("items_sha256"),
        (F.coalesce("n_hit", F.lit(0)) > 0).alias("contaminated"),
    )
