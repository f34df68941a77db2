"""Benchmark decontamination by a document-partitioned positional inverted index.

The index holds one posting (term, row, position) for every training token and
knows nothing of any test set, so one index serves as many of them as come.  It
is written where the scan task read the documents, every file sorted by term:
no posting is moved, so a frequent term or a hot source cannot pile up anywhere,
and a search for a few terms skips the row groups of all others.

A phrase search goes from the rarest terms of its windows (by their counts in
the index): the list of the rarest term is shifted by its offset in the window,
each further list only thins out the (document, window, shift) triples that are
left, and what three lists agree on is checked against all remaining terms.

Only built-in expressions are used.  What is broadcast belongs to the test set,
or are row numbers that have been counted; beyond ``BROADCAST_ROWS`` the same
joins shuffle.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .workspace import Workspace

#: What separates words (A-Z are lower-cased first, so they are word characters here).
BETWEEN = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

WINDOW = 10
ANCHORS = 3
BROADCAST_ROWS = 1_000_000
_END = "\u0000"


def _small(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def _ascii(word) -> F.Column:
    return F.octet_length(word) == F.char_length(word)


def test_items(items: DataFrame, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """(iid, item, words): equal rows once, items without words left out; a null id counts as the empty string."""
    lowered = F.translate(F.coalesce(F.col(text_col).cast("string"), F.lit("")), UPPER, LOWER)
    words = F.filter(F.split(lowered, BETWEEN), lambda w: w != "")
    item = F.coalesce(F.col(id_col).cast("string"), F.lit(""))
    return items.select(item.alias("item"), words.alias("words")).filter(F.size("words") > 0).distinct().withColumn("iid", F.xxhash64("item", "words"))


def build_index(docs: DataFrame, work: Workspace, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Write the index: (term, rid, pos, doc_id) sorted by term in every file; each row also has a posting of the null term, whose pos is its word count.

    ``rid`` numbers the rows, so repeated ids stay apart; only null terms carry the doc_id.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    low = F.when(_ascii(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))  # the same where all is ASCII, and faster
    words = docs.select(F.monotonically_increasing_id().alias("rid"), F.col(id_col).alias("doc_id"), F.split(low, BETWEEN).alias("w"))
    lead, last = (F.element_at("w", 1) == "").cast("int"), ((F.size("w") > 1) & (F.element_at("w", -1) == "")).cast("int")
    words = words.select("rid", "doc_id", lead.alias("lead"), (F.size("w") - lead - last).alias("n"), F.posexplode(F.concat("w", F.array(F.lit(_END)))).alias("at", "word")).filter("word <> ''")
    end = F.col("word") == _END
    rows = words.select(F.when(~end, F.xxhash64("word")).alias("term"), "rid", F.when(end, F.col("n")).otherwise(F.col("at") - F.col("lead")).cast("int").alias("pos"), F.when(end, F.col("doc_id")).alias("doc_id"))
    return work.save(rows.sortWithinPartitions("term", "rid", "pos"), "index")


def listed(index: DataFrame, terms: DataFrame) -> DataFrame:
    """(term, rid, pos) of some ``terms(term)``, a distinct few of the index's."""
    return index.select("term", "rid", "pos").join(_small(terms, terms.count()), "term", "left_semi")


def _places(items: DataFrame) -> DataFrame:
    return items.select("iid", F.size("words").alias("len"), F.posexplode("words").alias("ipos", "v")).withColumn("term", F.xxhash64("v")).drop("v")


def _windows(items: DataFrame, counts: DataFrame, window: int) -> DataFrame:
    """(iid, start, ipos, term, rank): the places of every window, rarest first; windows with a term that the index lacks are left out."""
    places = _places(items).join(_small(counts, counts.count()), "term", "left")
    starts = F.sequence(F.greatest(F.col("ipos") - (window - 1), F.lit(0)), F.least(F.col("ipos"), F.greatest(F.col("len") - window, F.lit(0))))
    inside = places.withColumn("start", F.explode(starts))
    per = Window.partitionBy("iid", "start")
    ranked = inside.withColumn("absent", F.max(F.col("cf").isNull().cast("int")).over(per)).withColumn("rank", F.row_number().over(per.orderBy("cf", "ipos")))
    return ranked.filter("absent = 0").select("iid", "start", "ipos", "term", "rank")


def term_counts(index: DataFrame, items: DataFrame, work: Workspace) -> DataFrame:
    """(term, cf) for the items' terms that the index has."""
    vocabulary = work.save(_places(items).select("term").distinct(), "vocabulary")
    return work.save(listed(index, vocabulary).groupBy("term").agg(F.count("*").alias("cf")), "counts")


def anchor_sets(items: DataFrame, counts: DataFrame, window: int = WINDOW, anchors: int = ANCHORS) -> DataFrame:
    """(iid, set, need, rank, ipos, term): the rarest places of every window; windows with the same ones share a set."""
    rare = _windows(items, counts, window).filter(F.col("rank") <= anchors)
    sets = rare.groupBy("iid", "start").agg(F.sort_array(F.collect_list(F.struct("rank", "ipos", "term"))).alias("p"))  # at most ``anchors`` each
    sets = sets.select("iid", "p").distinct().withColumn("set", F.xxhash64("iid", "p"))
    return sets.select("iid", "set", F.size("p").alias("need"), F.explode("p").alias("x")).select("iid", "set", "need", "x.rank", "x.ipos", "x.term")


def phrase_matches(index: DataFrame, items: DataFrame, work: Workspace, window: int = WINDOW) -> DataFrame:
    """(rid, iid, first, last): the words of a row that consecutive windows of an item cover, end included."""
    counts = term_counts(index, items, work)
    sets = work.save(anchor_sets(items, counts, window), "anchors")
    left = None
    for rank in range(1, ANCHORS + 1):
        asked = sets.filter(F.col("rank") == rank)
        postings = index.select("term", "rid", "pos")
        if left is not None:  # only rows that are still in the running
            rows = work.save(left.filter(F.col("need") >= rank).select("rid").distinct(), f"rows{rank}")
            postings = postings.join(_small(rows, rows.count()), "rid", "left_semi")
        shifted = postings.join(_small(asked, asked.count()), "term").select("rid", "iid", "set", "need", (F.col("pos") - F.col("ipos")).alias("shift"))
        if left is None:
            left = shifted  # below zero where a text begins in the middle of an item
        else:
            on = left.filter(F.col("need") >= rank).join(shifted.select("rid", "set", "shift"), ["rid", "set", "shift"], "left_semi")
            left = work.save(on.unionByName(left.filter(F.col("need") < rank)), f"left{rank}")
    triples = work.save(left.select("rid", "iid", "shift").distinct(), "triples")
    rows = work.save(triples.select("rid").distinct(), "rows")
    places = _places(items)
    wanted = triples.join(_small(places, items.agg(F.sum(F.size("words"))).first()[0] or 0), "iid").withColumn("pos", F.col("shift") + F.col("ipos"))
    near = listed(index, counts.select("term")).join(_small(rows, rows.count()), "rid", "left_semi")
    agree = wanted.join(near, ["rid", "pos", "term"])
    island = F.col("ipos") - F.row_number().over(Window.partitionBy("rid", "iid", "shift").orderBy("ipos"))
    runs = agree.withColumn("island", island).groupBy("rid", "iid", "shift", "island").agg(F.min("pos").alias("first"), F.max("pos").alias("last"), F.count("*").alias("k"), F.first("len").alias("len"))
    return runs.filter(F.col("k") >= F.least(F.lit(window), F.col("len"))).select("rid", "iid", "first", "last")


def proximity_matches(index: DataFrame, items: DataFrame, work: Workspace, slop: int = 20, window: int = WINDOW) -> DataFrame:
    """(rid, iid, pos): occurrences of a window's rarest term with all words of the window within ``slop`` words of it, in any order.

    A word that a window has twice needs two places.  Occurrences are dealt into
    blocks of ``slop`` words and meet the neighbouring blocks only, so a pair of
    frequent terms costs what lies near, not the product of their lists; rarer
    terms thin out the candidates before the others are read.
    """
    counts = term_counts(index, items, work)
    ranked = work.save(_windows(items, counts, window).withColumn("win", F.xxhash64("iid", "start")), "windows")
    needed = ranked.groupBy("win", "term").agg(F.count("*").alias("m"), F.min("rank").alias("rank"))
    needed = work.save(needed.withColumn("turn", F.row_number().over(Window.partitionBy("win").orderBy("rank"))), "needed")
    size = needed.count()
    block = F.floor(F.col("pos") / slop)
    head = ranked.filter("rank = 1").select("iid", "win", "term")
    left = work.save(index.select("term", "rid", "pos").join(_small(head, head.count()), "term").select("rid", "iid", "win", F.col("pos").alias("p")), "near0")
    for step, (lo, hi) in enumerate(((1, 1), (2, 2), (3, window)), 1):  # the rarest term may be needed more than once
        asked = needed.filter(F.col("turn").between(lo, hi))
        rows = work.save(left.select("rid").distinct(), f"nearrows{step}")
        about = index.select("term", "rid", "pos").join(_small(rows, rows.count()), "rid", "left_semi").join(_small(asked, size), "term")
        spread = left.withColumn("block", F.explode(F.array(*[F.floor(F.col("p") / slop) + i for i in (-1, 0, 1)])))
        close = spread.join(about.withColumn("block", block), ["rid", "win", "block"]).filter(F.abs(F.col("pos") - F.col("p")) <= slop)
        full = close.groupBy("rid", "iid", "win", "p", "term").agg(F.count("*").alias("k"), F.first("m").alias("m")).filter("k >= m").groupBy("rid", "iid", "win", "p").agg(F.count("*").alias("got"))
        want = asked.groupBy("win").agg(F.count("*").alias("want"))
        met = left.join(full, ["rid", "iid", "win", "p"], "left").join(_small(want, size), "win", "left")
        left = work.save(met.filter("coalesce(got, 0) = coalesce(want, 0)").select("rid", "iid", "win", "p"), f"near{step}")
    return left.select("rid", "iid", F.col("p").alias("pos")).distinct()


def _rows_of(index: DataFrame) -> DataFrame:
    """(rid, doc_id, n_words) of every indexed row."""
    return index.filter("term IS NULL").select("rid", "doc_id", F.col("pos").cast("long").alias("n_words"))


def contamination(docs: DataFrame | None, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, index: DataFrame | None = None) -> DataFrame:
    """Per row of ``docs``: (doc_id, n_words, n_hit, n_items, items_sha256, contaminated).

    A word is hit when it lies inside an occurrence of ``window`` consecutive
    words of an item (all of a shorter item).  Null and empty texts have no
    words; null and repeated ids keep their rows; equal items count once, and
    ``n_items`` counts ids; empty tables give no rows, or no hits.  Other columns
    are ignored.  With an ``index`` of earlier, texts are not read again.
    """
    work = Workspace(items.sparkSession, "positional")
    index = build_index(docs, work, id_col, text_col) if index is None else index
    items = work.save(test_items(items), "items")
    spans = work.save(phrase_matches(index, items, work, window), "spans")
    work.drop("anchors", "triples", "rows", "vocabulary", "counts", *[f"{n}{i}" for n in ("rows", "left") for i in range(2, ANCHORS + 1)])
    hit = spans.select("rid", F.explode(F.sequence("first", "last")).alias("pos")).distinct().groupBy("rid").agg(F.count("*").alias("n_hit"))
    which = spans.select("rid", "iid").distinct().join(_small(items.select("iid", "item"), items.count()), "iid")
    which = which.groupBy("rid").agg(F.sort_array(F.collect_set("item")).alias("items"))
    out = _rows_of(index).join(hit.join(which, "rid"), "rid", "left")
    ids = F.coalesce("items", F.array().cast("array<string>"))
    n_hit = F.coalesce("n_hit", F.lit(0)).cast("long")
    return out.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size(ids).cast("long").alias("n_items"), F.sha2(F.concat_ws(",", ids).cast("binary"), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"))


def near_items(index: DataFrame, items: DataFrame, slop: int = 20, window: int = WINDOW) -> DataFrame:
    """Per indexed row and item whose words it has close together in any order: (doc_id, item, n_places)."""
    work = Workspace(items.sparkSession, "proximity")
    items = work.save(test_items(items), "items")
    found = proximity_matches(index, items, work, slop, window).join(_small(items.select("iid", "item"), items.count()), "iid")
    found = found.select("rid", "item", "pos").distinct().groupBy("rid", "item").agg(F.count("*").alias("n_places"))
    return _rows_of(index).join(found, "rid").select("doc_id", "item", "n_places")


def op6_positional_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents`` against all ``benchmark`` items."""
    return contamination(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op6_proximity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that have all words of a ``benchmark`` window within twenty words of its rarest, in any order."""
    index = build_index(spark.read.parquet(f"{sf_dir}/documents.parquet"), Workspace(spark, "index"))
    return near_items(index, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


_FOLD = f"translate(coalesce(text, ''), '{UPPER}', '{LOWER}')"
_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"

OP6_SQL = rf"""
WITH d AS (SELECT doc_id, row_number() OVER () AS rid, regexp_extract_all({_FOLD}, '{_WORD}') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all({_FOLD}, '{_WORD}') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(len(w), {WINDOW}) AS k, array_to_string(w[i : i + least(len(w), {WINDOW}) - 1], ' ') AS phrase
       FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - {WINDOW}, 0) + 2)) AS i FROM b WHERE len(w) > 0)),
ks AS (SELECT DISTINCT k FROM bw),
dw AS (SELECT rid, k, i, array_to_string(w[i : i + k - 1], ' ') AS phrase
       FROM (SELECT rid, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM d, ks WHERE len(w) >= k)),
m AS (SELECT rid, dw.k, i, item_id FROM dw JOIN bw ON dw.phrase = bw.phrase AND dw.k = bw.k),
h AS (SELECT rid, count(DISTINCT p) AS n_hit FROM (SELECT rid, unnest(range(i, i + k)) AS p FROM m) GROUP BY rid),
t AS (SELECT rid, count(*) AS n_items, sha256(string_agg(s, ',' ORDER BY s)) AS items_sha256
      FROM (SELECT DISTINCT rid, coalesce(CAST(item_id AS VARCHAR), '') AS s FROM m) GROUP BY rid)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       coalesce(items_sha256, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (rid) LEFT JOIN t USING (rid)
"""
