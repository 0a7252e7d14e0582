"""Cross-document line frequency: lines that too many documents of a host share are removed, depleted documents rejected.

DataFrame functions only.  Every text is read twice: for the hashes of its normalised lines, from which the frequent lines of the
hosts are found, and for its own measures and the text without those lines.  Documents of a host count once per distinct text, so
copies do not make a line frequent.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .runtime import BROADCAST_ROWS, let, materialise

#: A line is frequent if more distinct texts of its host have it than the first says, and than the share or the fixed number, whichever is less.
LEAST_TEXTS, LARGEST_SHARE, MOST_TEXTS = 20, 0.10, 200
#: Frequent lines of a host that each of its rows may be compared with; beyond it, rows are joined with their own lines.
HOST_LINES = 2_000
#: A document is depleted if more than this share of its words is in frequent lines.
DEPLETED = 0.5

_BLANK = r"\x20\x09-\x0D"


def _words(text: Column) -> Column:
    trimmed = F.btrim(text, F.lit(" \t\n\x0b\x0c\r"))
    return let(trimmed, lambda t: F.when(t == "", F.array().cast("array<string>")).otherwise(F.split(t, f"[{_BLANK}]+")))


def _dup_lines(text: Column) -> Column:
    full = F.filter(F.split(text, "\n"), lambda x: F.rlike(x, F.lit(f"[^{_BLANK}]")))
    return let(full, lambda x: F.size(x) - F.size(F.array_distinct(x)))


def _covered(positions: Column) -> Column:
    """Words covered by windows of three words at ascending positions."""
    step = F.transform(positions, lambda p, i: F.when(i == 0, F.lit(3)).otherwise(F.least(F.lit(3), p - F.get(positions, i - 1))).cast("long"))
    return F.aggregate(step, F.lit(0).cast("long"), lambda acc, x: acc + x)


def _repeat_words(words: Column) -> Column:
    """Words in three-word windows that occur twice or more.

    Windows sort as one long each: the upper bits of their hash, then the position, in as many low bits as the text needs.  Where the
    shortened hashes meet more often than the full ones, pairs of full hash and position are sorted instead.
    """
    n = F.size(words)

    def from_hashes(h: Column) -> Column:
        bits = F.ceil(F.log2(F.size(h) + F.lit(1.0))).cast("int")
        packed = lambda b: F.sort_array(F.transform(h, lambda x, i: F.call_function("shiftleft", x, b).bitwiseOR(i.cast("long"))))
        upper = lambda x, b: F.call_function("shiftrightunsigned", x, b)

        def short(b: Column) -> Column:
            def twice(s: Column) -> Column:
                same = lambda x, y: F.coalesce(upper(x, b) == upper(y, b), F.lit(False))
                low = F.call_function("shiftleft", F.lit(1).cast("long"), b) - 1
                hit = F.filter(s, lambda x, i: same(x, F.get(s, i - 1)) | same(x, F.get(s, i + 1)))
                kinds = F.size(F.filter(s, lambda x, i: ~same(x, F.get(s, i - 1))))
                count = let(F.sort_array(F.transform(hit, lambda x: x.bitwiseAND(low))), _covered)
                return F.when(kinds == F.size(F.array_distinct(h)), count)

            return let(packed(b), twice)

        def full() -> Column:
            pairs = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.cast("long").alias("i"))))
            same = lambda x, y: F.coalesce(x["h"] == y["h"], F.lit(False))
            hit = lambda s: F.filter(s, lambda x, i: same(x, F.get(s, i - 1)) | same(x, F.get(s, i + 1)))
            return let(let(pairs, lambda s: F.sort_array(F.transform(hit(s), lambda x: x["i"]))), _covered)

        return F.coalesce(let(bits, short), full())

    windows = F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)))
    return F.when(n < 4, F.lit(0).cast("long")).otherwise(let(windows, from_hashes))


def _lines(text: Column) -> Column:
    """Hash of each line, null for one without a word: lower case, digit runs as 0, single blanks."""
    plain = F.regexp_replace(F.regexp_replace(F.lower(text), "[0-9]+", "0"), r"[\x20\x09\x0B-\x0D]+", " ")
    return F.transform(F.transform(F.split(plain, "\n"), lambda x: F.trim(x)), lambda x: F.when(x != "", F.xxhash64(x)))


def _rows(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("host"), text.alias("text"))


def hashed_lines(rows: DataFrame) -> DataFrame:
    """Per row: host, text key and the distinct hashes of the lines."""
    return rows.select("host", F.md5("text").alias("text_key"), F.array_compact(F.array_distinct(_lines(F.col("text")))).alias("lines"))


def frequent_lines(texts: DataFrame, least: int = LEAST_TEXTS, share: float = LARGEST_SHARE, most: int = MOST_TEXTS) -> DataFrame:
    """(host, h): lines in more than ``least`` texts of their host, and in more than ``share`` of them or more than ``most``.

    Counts combine before every shuffle; a hot host is dealt out by its lines.
    """
    hosts = texts.groupBy("host").agg(F.count("*").alias("texts"))
    counts = texts.select("host", F.explode("lines").alias("h")).groupBy("host", "h").agg(F.count("*").alias("n")).where(F.col("n") > least)
    return counts.join(hosts, "host").where((F.col("n") > share * F.col("texts")) | (F.col("n") > most)).select("host", "h")


def line_frequency(docs: DataFrame, least: int = LEAST_TEXTS, share: float = LARGEST_SHARE, most: int = MOST_TEXTS, depleted: float = DEPLETED, host_lines: int = HOST_LINES) -> DataFrame:
    """(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, n_removed_words, text) for each row.

    ``text`` is without its frequent lines, all others as they were; it is given for rejected documents (not ``kept``) too.

    ``docs``: (doc_id, text, source).  Null text has no words, fails and comes back empty; null source is a host of its own (that of
    the empty name).  Null ids and repeated rows get a row each.  Texts of any length are read whole; extra columns are
    not read; no documents give no rows.
    """
    rows = _rows(docs)
    texts = materialise(hashed_lines(rows), "lines").dropDuplicates(["host", "text_key"])
    frequent = materialise(frequent_lines(texts, least, share, most), "frequent")
    n, largest = frequent.groupBy("host").count().agg(F.coalesce(F.sum("count"), F.lit(0)), F.coalesce(F.max("count"), F.lit(0))).first()
    if n <= BROADCAST_ROWS and largest <= host_lines:
        found = rows.join(F.broadcast(frequent.groupBy("host").agg(F.collect_list("h").alias("frequent"))), "host", "left")
    else:
        # each distinct text gets its own frequent lines; a hot host is dealt out by lines, then by texts
        hits = texts.select("host", "text_key", F.explode("lines").alias("h")).join(frequent, ["host", "h"]).groupBy("host", "text_key").agg(F.collect_list("h").alias("frequent"))
        found = rows.withColumn("text_key", F.md5("text")).join(hits, ["host", "text_key"], "left").drop("text_key")
    text = F.col("text")
    of_words = let(_words(text), lambda w: F.struct(F.size(w).cast("long").alias("n_words"), F.length(F.array_join(w, "")).cast("long").alias("word_chars"), _repeat_words(w).alias("n_repeat_words")))
    left = let(cleaned_text(text, F.col("frequent")), lambda t: F.struct(t.alias("text"), F.when(t != text, F.size(_words(t)).cast("long")).alias("n_left")))
    out = found.select(
        "doc_id", of_words.alias("of_words"), F.regexp_count("text", F.lit("[#*$%&|<>]")).cast("long").alias("n_symbols"), _dup_lines(text).cast("long").alias("n_dup_lines"), left.alias("left"),
    ).select("doc_id", "of_words.*", "n_symbols", "n_dup_lines", "left.*")
    removed = F.coalesce(F.col("n_words") - F.col("n_left"), F.lit(0).cast("long"))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return out.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"),
        (~failed & (removed <= depleted * F.col("n_words"))).alias("kept"), removed.alias("n_removed_words"), "text",
    )


def cleaned_text(text: Column, frequent: Column) -> Column:
    """``text`` without the lines whose hash is in the array ``frequent``, which may be null."""

    def without(h: Column) -> Column:
        there = lambda i, hits: F.coalesce(F.array_contains(hits, F.get(h, i)), F.lit(False))
        rest = lambda hits: F.array_join(F.filter(F.split(text, "\n"), lambda x, i: ~there(i, hits)), "\n")
        return let(F.array_intersect(h, frequent), lambda hits: F.when(F.size(hits) == 0, text).otherwise(rest(hits)))

    return F.when(frequent.isNull(), text).otherwise(let(_lines(text), without))
