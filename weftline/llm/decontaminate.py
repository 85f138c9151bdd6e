"""Benchmark decontamination with DataFrame functions alone.

The n-grams of the benchmark's items, normalised, form a hash set that is
broadcast while its counted size stays under a bound and joined by shuffle
beyond it.  A scan over the documents hashes the window at every word, probes
the set and compares the words of a hit with those of the n-gram, so hash
collisions never count.  Hits flag documents, cut spans or drop documents.

Defined cases.  A null text or one without words has no windows.  An item with
fewer words than ``n``, but not none, is one window of that many words.  Rows
that repeat are kept and judged alike.  Extra columns of any name pass through;
``flag`` replaces those named like its results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ASCII_CAPITALS, ASCII_SMALL, column, free_name

#: ASCII without letters and digits, in a Java pattern (capitals belong to words).
GAPS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"

#: Bytes of the benchmark's windows, counted before, up to which the hash set is broadcast.
BROADCAST_BYTES = 64 << 20
#: Parts of a window's rows in the join by shuffle.
SALTS = 16


def cased_words(text: Column) -> Column:
    """Words with their capitals; as many as there are normalised words."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), GAPS), "")


def normal_words(text: Column) -> Column:
    return cased_words(F.translate(text, ASCII_CAPITALS, ASCII_SMALL))


def window_hash(words: Column, start: Column, size: int) -> Column:
    return F.xxhash64(*[F.get(words, start + F.lit(j)) for j in range(size)])


def windows_of(benchmark: DataFrame, n: int, item: str, text: str) -> DataFrame:
    """One row per distinct window: size, hash, words, sorted distinct items."""
    words = benchmark.select(column(item).cast("string").alias("item"), normal_words(column(text)).alias("gram_words"))
    sized = words.filter(F.size("gram_words") > 0).withColumn("size", F.least(F.lit(n), F.size("gram_words")))
    starts = F.sequence(F.lit(0), F.size("gram_words") - F.col("size"))
    grams = sized.select("item", "size", F.explode(starts).alias("at"), "gram_words").select(
        "item", "size", F.slice("gram_words", F.col("at") + 1, F.col("size")).alias("gram")
    )
    return grams.groupBy("size", "gram").agg(F.array_sort(F.collect_set("item")).alias("items"))


def hits(texts: DataFrame, benchmark: DataFrame, n: int = 10, *, item: str = "item_id", item_text: str = "text") -> DataFrame:
    """Of texts (id, key, words): id, key, start, size, items of each place where a window occurs.

    One scan serves windows of all sizes.
    """
    grams = windows_of(benchmark, n, item, item_text)
    bytes_of = F.octet_length(F.array_join("gram", " ")) + F.octet_length(F.array_join("items", " ")) + 64 + 24 * (F.size("gram") + F.size("items"))
    counted = {r["size"]: r["bytes"] for r in grams.groupBy("size").agg(F.sum(bytes_of).alias("bytes")).collect()}
    small = sum(counted.values()) <= BROADCAST_BYTES
    sizes = sorted(counted) or [n]

    def keyed(words: Column, start: Column) -> Column:
        """The hash of the window of each size."""
        return F.array(*[F.struct(F.lit(size).alias("size"), window_hash(words, start, size).alias("h")) for size in sizes])

    own = keyed(F.col("gram"), F.lit(0))[F.array_position(F.array(*map(F.lit, sizes)), F.col("size")).cast("int") - 1]
    side = grams.select(own.alias("of"), "gram", "items").select("of.size", "of.h", "gram", "items")
    at = texts.select("id", "key", "words", F.posexplode("words").alias("start", "first"))
    if len(sizes) == 1:
        probe = at.select("id", "key", "words", "start", F.lit(sizes[0]).alias("size"), window_hash(F.col("words"), F.col("start"), sizes[0]).alias("h"))
    else:
        probe = at.select("id", "key", "words", "start", F.explode(keyed(F.col("words"), F.col("start"))).alias("of")).select("id", "key", "words", "start", "of.size", "of.h")
    probe = probe.filter(F.col("start") <= F.size("words") - F.col("size"))
    window = F.slice("words", F.col("start") + 1, F.col("size"))
    if small:  # the words stay where they are: they are looked at for hits alone
        met = probe.join(F.broadcast(side), ["size", "h"]).filter(window == F.col("gram"))
    else:  # a window moves with its own words, never with the document's; a frequent one is dealt by salts
        salted = side.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        salt = F.pmod(F.xxhash64("id", "start"), F.lit(SALTS)).cast("int").alias("salt")
        met = probe.select("id", "key", "start", "size", "h", window.alias("own"), salt).join(salted, ["size", "h", "salt"]).filter("own = gram")
    return met.select("id", "key", "start", "size", "items")


def covered(spans: Column) -> Column:
    """Words in the union of sorted (start, size) spans: the sum of what each adds."""
    zero = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).alias("end"))

    def add(state: Column, span: Column) -> Column:
        begin, end = F.greatest(span["start"], state["end"]), span["start"] + span["size"]
        return F.struct(
            (state["n"] + F.greatest(F.lit(0), end - begin)).cast("long").alias("n"),
            F.greatest(end, state["end"]).alias("end"),
        )

    return F.aggregate(spans, zero, add, lambda s: s["n"])


def flag(docs: DataFrame, benchmark: DataFrame, n: int = 10, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with n_words, n_hit, items, spans and contaminated; columns of these names are replaced."""
    found = judged(docs, benchmark, n, doc_id, text)
    names = ["n_words", "n_hit", "items", "spans", "contaminated"]
    gone = {c for c in names if c not in (doc_id.lower(), text.lower())}
    result = column(found.columns[-1])
    return found.select(*[column(c) for c in docs.columns if c.lower() not in gone], *[result[c].alias(c) for c in names])


def judged(docs: DataFrame, benchmark: DataFrame, n: int, doc_id: str, text: str) -> DataFrame:
    """``docs`` and behind all its columns one struct of results, under a name of its own.

    Two rows with one id and different texts are told apart by a hash of the text.
    """
    result = free_name(docs, "judged")
    keys = F.struct(column(doc_id).alias("id"), F.xxhash64(column(text), F.length(column(text))).alias("key"))
    texts = docs.select(keys.alias("of"), normal_words(column(text)).alias("words")).select("of.id", "of.key", "words")
    per_doc = (
        hits(texts, benchmark, n)
        .groupBy("id", "key")
        .agg(
            F.array_sort(F.collect_set(F.struct("start", "size"))).alias("spans"),
            F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"),
        )
        .select(F.struct("id", "key").alias(free_name(docs, "hit_of")), F.struct(covered(F.col("spans")).alias("n_hit"), "items", "spans").alias(free_name(docs, "hit")))
    )
    own = docs.withColumn(result, F.struct(keys["id"].alias("id"), keys["key"].alias("key"), F.size(cased_words(column(text))).cast("long").alias("n_words")))
    of, hit = (column(c) for c in per_doc.columns)
    on = column(result)["id"].eqNullSafe(of["id"]) & (column(result)["key"] == of["key"])
    n_hit = F.coalesce(hit["n_hit"], F.lit(0).cast("long"))
    return own.join(per_doc, on, "left").select(
        *[column(c) for c in docs.columns],
        F.struct(
            column(result)["n_words"].alias("n_words"),
            n_hit.alias("n_hit"),
            F.coalesce(hit["items"], F.array().cast("array<string>")).alias("items"),
            F.coalesce(hit["spans"], F.array().cast("array<struct<start:int,size:int>>")).alias("spans"),
            (n_hit > 0).alias("contaminated"),
        ).alias(result),
    )


def decontaminate(docs: DataFrame, benchmark: DataFrame, n: int = 10, *, how: str = "documents", doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Removes hit documents, or (``how="spans"``) the hit words; columns of any name stay as they were.

    With spans, the words left of a hit document are joined by one space and
    its text is in normalised form; other documents keep their texts.
    """
    found = judged(docs, benchmark, n, doc_id, text)
    result = column(found.columns[-1])
    if how == "documents":
        return found.filter(~result["contaminated"]).drop(found.columns[-1])
    left = F.filter(
        normal_words(column(text)), lambda w, i: ~F.exists(result["spans"], lambda s: (i >= s["start"]) & (i < s["start"] + s["size"]))
    )
    cut = F.when(result["contaminated"], F.array_join(left, " ")).otherwise(column(text)).alias(text)
    return found.select(*[cut if c == text else column(c) for c in docs.columns])
