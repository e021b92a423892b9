"""Benchmark decontamination by winnowing, with exact extension of hits.

A shared span of `span` words holds span-k+1 hashes of k words; keeping the least hash of every such
window of hashes, any two texts that share the span keep the same hash for it. So the benchmark is
reduced to the least hashes of its windows, each document to its own distinct ones, and the two are
joined. Around what meets, the runs of windows whose least hash was found are cut out as text,
compared word by word with the benchmark's windows, and turned into exact covered words and items.

Runs that are equal in many documents are compared once. An item with fewer than `span` words is
one window of its own length; each such length is winnowed for itself.

Defined results: null and empty texts have no words; an item without words has no window; equal
items are named each; a null item_id counts as one item shown as ''. Repeated documents are judged
each. Extra columns of the documents are dropped by `contamination`, kept by `clean`.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from celldiv.llm.common import ascii_lower, counted, let, persisted, small

#: ASCII that is neither letter nor digit parts words; everything beyond ASCII belongs to them.
BREAK = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: The same before lower-casing.
BREAK_ANY_CASE = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
#: A side of more fingerprints or keys than this is shuffled, not broadcast (about 30 bytes each).
BROADCAST_ROWS = 2_000_000


def words_of(text: Column) -> Column:
    return F.filter(F.split(ascii_lower(F.coalesce(text, F.lit(""))), BREAK), lambda w: w != "")


def _least_hashes(words: Column, span: int) -> Column:
    """For each window of `span` words the least hash of its k-word grams, k = half the span."""
    k = (span + 1) // 2
    many = span - k + 1

    def minima(h: Column) -> Column:
        at = F.sequence(F.lit(0), F.size(h) - many)
        return F.transform(at, lambda i: F.least(*[F.get(h, i + j) for j in range(many)]) if many > 1 else F.get(h, i))

    grams = F.transform(F.sequence(F.lit(0), F.size(words) - k), lambda i: F.xxhash64(*[F.get(words, i + j) for j in range(k)]))
    return F.when(F.size(words) < span, F.array().cast("array<bigint>")).otherwise(let(grams, minima))


def _key(text: Column) -> list[Column]:
    return [F.xxhash64(text).alias("k1"), F.xxhash64(F.lit("k"), text).alias("k2"), F.octet_length(text).alias("k3")]


KEY = ["k1", "k2", "k3"]


def benchmark_windows(items: DataFrame, span: int) -> DataFrame:
    """(width, window, items): every distinct window text with the ids of the items that have it."""
    have = items.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item"), words_of(F.col("text")).alias("w")).where(F.size("w") > 0)
    cut = let(F.col("w"), lambda w: let(F.least(F.size(w), F.lit(span)), lambda n: F.transform(F.sequence(F.lit(1), F.size(w) - n + 1), lambda i: F.struct(n.alias("width"), F.array_join(F.slice(w, i, n), " ").alias("window")))))
    return have.select("item", F.explode(cut).alias("x")).groupBy("x.width", "x.window").agg(F.collect_set("item").alias("items"))


def _placed_prints(words: Column, span: int) -> Column:
    """(width, print, a, b) for each stretch a..b of windows that keep one and the same hash."""
    def cut(h: Column) -> Column:
        begins = F.filter(F.transform(h, lambda x, i: F.when(F.coalesce(F.get(h, i - 1) != x, F.lit(True)), i)), lambda i: i.isNotNull())
        return let(begins, lambda at: F.transform(at, lambda p, j: F.struct(
            F.lit(span).alias("width"), F.get(h, p).alias("print"), p.alias("a"), (F.coalesce(F.get(at, j + 1), F.size(h)) - 1).alias("b"))))

    return let(_least_hashes(words, span), cut)


def _runs(docs: DataFrame, windows: DataFrame, widths: list[int]) -> DataFrame:
    """(k1, k2, k3, width, start, run): maximal stretches of distinct texts whose windows all met the benchmark's fingerprints.

    All widths are winnowed in one pass, and a hash is kept with its places, so a text is read again only to cut out
    what was found. Copies of a text are folded before texts travel.
    """
    own = [windows.where(F.col("width") == w).select("width", F.explode(_least_hashes(F.split("window", " "), w)).alias("print")) for w in widths]
    prints = reduce(DataFrame.unionByName, own).distinct()
    texts = docs.select(F.col("text").alias("t")).where(F.col("t").isNotNull())
    mine = texts.select(*_key(F.col("t")), F.explode(let(words_of(F.col("t")), lambda w: F.concat(*[_placed_prints(w, n) for n in widths]))).alias("x")).select(*KEY, "x.*")
    met = mine.join(small(prints, BROADCAST_ROWS), ["width", "print"]).groupBy(*KEY, "width").agg(F.array_sort(F.collect_set(F.struct("a", "b"))).alias("at"))
    met = persisted(met)
    first = F.filter(F.transform("at", lambda x, j: F.when(F.coalesce(F.get("at", j - 1)["b"] != x["a"] - 1, F.lit(True)), x["a"])), lambda p: p.isNotNull())
    last = F.filter(F.transform("at", lambda x, j: F.when(F.coalesce(F.get("at", j + 1)["a"] != x["b"] + 1, F.lit(True)), x["b"])), lambda p: p.isNotNull())
    found = met.select(*KEY, "width", F.arrays_zip(first.alias("a"), last.alias("b")).alias("at"))
    keys, keyed = met.select(*KEY).distinct(), texts.select(*_key(F.col("t")), "t")
    if counted(keys, BROADCAST_ROWS):
        keyed = keyed.join(F.broadcast(keys), KEY, "left_semi")  # three numbers a row
    keyed = keyed.groupBy(*KEY).agg(F.any_value("t").alias("t")).join(found, KEY)
    cut = let(words_of(F.col("t")), lambda w: F.transform("at", lambda x: F.struct(x["a"].alias("start"), F.array_join(F.slice(w, x["a"] + 1, x["b"] - x["a"] + F.col("width")), " ").alias("run"))))
    return persisted(keyed.select(*KEY, "width", F.explode(cut).alias("s")).select(*KEY, "width", "s.start", "s.run"))


def _matched(runs: DataFrame, windows: DataFrame) -> DataFrame:
    """(width, run, places, items): per distinct run where the benchmark's windows begin in it, and whose they are."""
    one = runs.select("width", "run").distinct()
    cut = let(F.split("run", " "), lambda w: F.transform(F.sequence(F.lit(1), F.size(w) - F.col("width") + 1), lambda i: F.struct((i - 1).alias("at"), F.array_join(F.slice(w, i, F.col("width")), " ").alias("window"))))
    cuts = one.select("width", "run", F.explode(cut).alias("x")).select("width", "run", "x.at", "x.window")
    hits = cuts.join(small(windows, BROADCAST_ROWS // 10), ["width", "window"])
    return hits.groupBy("width", "run").agg(F.collect_set("at").alias("places"), F.array_distinct(F.flatten(F.collect_set("items"))).alias("items"))


def hits(docs: DataFrame, items: DataFrame, span: int = 10) -> DataFrame:
    """(k1, k2, k3, n_hit, items): per distinct contaminated text its covered words and the items found."""
    windows = persisted(benchmark_windows(items, span))
    widths = sorted(r[0] for r in windows.select("width").distinct().collect())  # at most `span` numbers
    runs = _runs(docs, windows, widths or [span])
    found = runs.join(_matched(runs, windows), ["width", "run"])
    found = found.select(*KEY, "items", F.transform("places", lambda p: F.struct((p + F.col("start")).alias("a"), (p + F.col("start") + F.col("width")).alias("b"))).alias("spans"))
    per = found.groupBy(*KEY).agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"), F.array_sort(F.flatten(F.collect_list("spans"))).alias("spans"))
    start = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).alias("end"))
    step = lambda s, x: F.struct((s["n"] + F.greatest(F.lit(0), x["b"] - F.greatest(x["a"], s["end"]))).cast("long").alias("n"), F.greatest(s["end"], x["b"]).alias("end"))
    return per.select(*KEY, F.aggregate("spans", start, step, lambda s: s["n"]).alias("n_hit"), "items")


def contamination(docs: DataFrame, items: DataFrame, span: int = 10) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated for every document row."""
    every = docs.select("doc_id", let(F.split(F.coalesce("text", F.lit("")), BREAK_ANY_CASE), lambda w: F.size(w) - (F.get(w, F.lit(0)) == "").cast("int") - ((F.size(w) > 1) & (F.element_at(w, -1) == "")).cast("int")).cast("long").alias("n_words"), *_key(F.col("text")))
    digest = lambda names: F.sha2(F.array_join(names, ",").cast("binary"), 256)
    found = persisted(hits(docs, items, span).select(*KEY, "n_hit", F.size("items").cast("long").alias("n_items"), digest(F.col("items")).alias("items_sha256")))
    got = every.join(small(found, BROADCAST_ROWS // 10), KEY, "left")  # about 100 bytes a row
    none = F.lit(0).cast("long")
    return got.select("doc_id", "n_words", F.coalesce("n_hit", none).alias("n_hit"), F.coalesce("n_items", none).alias("n_items"),
                      F.coalesce("items_sha256", digest(F.array().cast("array<string>"))).alias("items_sha256"), (F.coalesce("n_hit", none) > 0).alias("contaminated"))


def clean(docs: DataFrame, items: DataFrame, span: int = 10) -> DataFrame:
    """The documents, all columns, without those that hold a benchmark window."""
    found = persisted(hits(docs.select("text"), items, span).select(*[F.col(c).alias(f"__{c}") for c in KEY]))
    return docs.join(small(found, BROADCAST_ROWS), (F.xxhash64("text") == F.col("__k1")) & (F.xxhash64(F.lit("k"), F.col("text")) == F.col("__k2")) & (F.octet_length("text") == F.col("__k3")), "left_anti")
