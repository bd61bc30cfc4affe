"""Benchmark decontamination with a broadcast hash set of test n-grams, in DataFrame functions only.

Texts are lower-cased (A-Z) and cut into words.  A window is N consecutive words of a benchmark item, or all words of a shorter
item.  The driver holds the set of 64-bit keys of the distinct windows (a key hashes three words of a window and its length);
that set is part of the plan, so it reaches every task, and each document's word positions are tested against it inside
one expression over the word array: nothing is exploded or shuffled for positions that don't hit.  Positions that hit
are then joined with the windows' full word sequences, which decides.

The set's size is checked: past ``MAX_BROADCAST`` windows the keys are not sent out, but positions and windows meet in a
shuffled join.

Defined cases: null and empty texts have no words, items without words have no windows; a window of many items counts for each;
equal documents get equal results (rows that repeat stay separate); an empty table on either side gives no hits; other
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

N = 10
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Windows whose keys may be sent to every task (some 20 bytes each in a plan).
MAX_BROADCAST = 200_000
# The letters that are lowered.
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words(text: str | Column) -> Column:
    """The array of normalised words; empty for null."""
    text = F.col(text) if isinstance(text, str) else text
    return F.coalesce(F.regexp_extract_all(F.translate(text, UPPER, LOWER), F.lit(WORD), F.lit(0)), F.expr("cast(array() as array<string>)"))


def _key(w: Column, i: Column, n: int) -> Column:
    """Key of the window of n words that starts at position i (from 0)."""
    return F.xxhash64(F.lit(n), w[i], w[i + n // 2], w[i + (n - 1)])


def _starts(size: Column, n: int) -> Column:
    """Positions where a window of n words can start."""
    return F.when(size >= n, F.sequence(F.lit(0), size - n)).otherwise(F.expr("cast(array() as array<int>)"))


def windows(benchmark: DataFrame, n: int = N) -> DataFrame:
    """The distinct windows: their words (joined by spaces), length, key and the items that have them."""
    items = benchmark.select(F.col("item_id"), words("text").alias("w")).where(F.size("w") > 0)
    items = items.withColumn("len", F.least(F.size("w"), F.lit(n)))
    starts = items.select("item_id", "w", "len", F.explode(F.sequence(F.lit(0), F.size("w") - F.col("len"))).alias("i"))
    key = F.xxhash64(F.col("len"), F.col("w")[F.col("i")], F.col("w")[F.col("i") + F.floor(F.col("len") / 2).cast("int")], F.col("w")[F.col("i") + F.col("len") - 1])
    spans = starts.select("item_id", "len", F.array_join(F.slice("w", F.col("i") + 1, F.col("len")), " ").alias("window"), key.alias("key"))
    return spans.groupBy("window", "len", "key").agg(F.collect_set("item_id").alias("items"))


def hits(docs: DataFrame, benchmark: DataFrame, n: int = N, max_broadcast: int = MAX_BROADCAST) -> DataFrame:
    """All columns of ``docs`` in a struct ``row``, n_words, ``rid`` (0 or more), and ``found``: the verified hits (start, len, window)."""
    grams = windows(benchmark, n)
    # the benchmark is small against the corpus; its number of windows is checked, not assumed
    some = grams.select("len", "key", "window").limit(max_broadcast + 1).collect()
    few = len(some) <= max_broadcast
    lengths = sorted({row["len"] for row in some}) if few else list(range(1, n + 1))
    # a filter that also asks for the row id stays above this projection; else the optimizer would move the cutting into words
    # into the lambdas below, where it would run again for each word
    split = docs.select(F.struct(*docs.columns).alias("row"), words("text").alias("w"), F.monotonically_increasing_id().alias("rid"))

    def at(length: int) -> Column:
        """(start, len, window) of each position whose key, then whose words, are in the set."""
        starts, spot = _starts(F.size("w"), length), lambda i: F.struct(i.alias("start"), F.lit(length).alias("len"), F.array_join(F.slice("w", i + 1, F.lit(length)), " ").alias("window"))
        if not few:
            return F.transform(starts, spot)
        own = [row for row in some if row["len"] == length]
        likely = F.filter(starts, lambda i: _key(F.col("w"), i, length).isin(sorted({row["key"] for row in own})))
        return F.filter(F.transform(likely, spot), lambda s: s["window"].isin(sorted(row["window"] for row in own)))

    empty = F.expr("cast(array() as array<struct<start:int,len:int,window:string>>)")
    spots = F.concat(*(at(length) for length in lengths)) if lengths else empty
    rows = split.select("row", F.size("w").alias("n_words"), spots.alias("found"), "rid")
    if few:
        return rows
    # every position meets the windows in a shuffled join; positions of a document come back together by its row id
    each = rows.select("rid", F.explode("found").alias("spot"))
    true = each.join(grams.select("window"), F.col("spot.window") == F.col("window"), "left_semi").groupBy("rid").agg(F.collect_list("spot").alias("found"))
    return rows.drop("found").join(true, "rid", "left").select("row", "n_words", "rid", F.coalesce("found", empty).alias("found"))


def _covered(found: Column) -> Column:
    """How many words lie inside hits, each counted once."""
    spans = F.array_sort(F.transform(found, lambda h: F.struct(h["start"].alias("a"), (h["start"] + h["len"]).alias("b"))))
    # each hit covers what lies past the furthest end before it
    start = F.struct(F.lit(0).alias("end"), F.lit(0).alias("n"))
    step = lambda s, x: F.struct(F.greatest(s["end"], x["b"]).alias("end"), (s["n"] + F.greatest(F.lit(0), x["b"] - F.greatest(s["end"], x["a"]))).alias("n"))
    return F.aggregate(spans, start, step)["n"]


def contamination(docs: DataFrame, benchmark: DataFrame, n: int = N, max_broadcast: int = MAX_BROADCAST) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256 and contaminated of every document."""
    found = hits(docs.select("doc_id", "text"), benchmark, n, max_broadcast)
    slim = found.select(F.col("row.doc_id").cast("long").alias("doc_id"), F.col("n_words").cast("long").alias("n_words"), _covered(F.col("found")).cast("long").alias("n_hit"), F.array_distinct("found.window").alias("seen"), F.monotonically_increasing_id().alias("rid"))
    each = slim.select("rid", "doc_id", "n_words", "n_hit", F.explode_outer("seen").alias("window"))
    named = each.join(windows(benchmark, n).select("window", "items"), "window", "left").groupBy("rid", "doc_id", "n_words", "n_hit").agg(F.flatten(F.collect_list("items")).alias("items"))
    items = F.array_sort(F.array_distinct(F.transform("items", lambda i: i.cast("string"))))
    out = named.select("doc_id", "n_words", "n_hit", items.alias("items"))
    return out.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def remove_contaminated(docs: DataFrame, benchmark: DataFrame, max_hit_share: float = 0.0, n: int = N, max_broadcast: int = MAX_BROADCAST) -> DataFrame:
    """The documents, all columns, of which at most the given share of words lies inside benchmark windows; moves no document."""
    found = hits(docs, benchmark, n, max_broadcast)
    return found.where((F.col("rid") >= 0) & (_covered(F.col("found")) <= F.lit(float(max_hit_share)) * F.col("n_words"))).select("row.*")


def remove_spans(docs: DataFrame, benchmark: DataFrame, n: int = N, max_broadcast: int = MAX_BROADCAST) -> DataFrame:
    """The documents, all columns, without the words inside benchmark windows; what lies between words stays as it is.

    A text is cut into (what stands before a word, the word); pieces whose word is hit go.
    """
    found = hits(docs, benchmark, n, max_broadcast)
    bare = rf"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]*(?:[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+|$)"
    pieces = F.regexp_extract_all(F.col("row.text"), F.lit(bare), F.lit(0))
    spots = F.array_distinct(F.flatten(F.transform("found", lambda h: F.sequence(h["start"], h["start"] + h["len"] - 1))))
    kept = F.array_join(F.filter(pieces, lambda x, i: ~F.array_contains(F.col("spots"), i)), "")
    text = F.when(F.size("spots") > 0, kept).otherwise(F.col("row.text"))
    return found.withColumn("spots", spots).withColumn("kept", text).select(*(F.col("kept").alias(c) if c == "text" else F.col("row")[c].alias(c) for c in docs.columns))
