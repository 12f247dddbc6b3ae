"""Quality rules and cross-document line frequency, in DataFrame functions only.

Base rules count words, symbols, repeated lines and repeated three-word windows of each
text. Across documents, each line is normalised (lower case, digits as 0, white space
squeezed) and hashed with its host; a line that more than ``max_docs`` documents of one
host hold is boilerplate and goes. A document of which less than ``min_kept`` of the
characters in words remain is depleted and rejected.

Counting is a two-step aggregate over 8-byte hashes: (host and line, document) pairs,
then lines; each combines before its shuffle, so a host with a third of all rows is no
hot key. The lines over the limit are written to the checkpoint folder; while their measured
number is below ``BROADCAST_ROWS`` they meet the documents' lines without a shuffle,
beyond it through an ordinary join.

Defined results: null and empty texts have no word and fail the base rules; a null host
is a host of its own; repeated rows of one key count as one document and each give a
row (rows are joined by key, so equal keys must have equal texts); rows without a key
are one document; blank lines are never counted or removed; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import boxed, checkpointed, picked, position, table, unboxed

SPACE = "[\\x20\\x09-\\x0D]"  # fixed value
SYMBOLS = "[#*$%&|<>]"  # fixed value
MAX_DOCS, MIN_KEPT, MIN_WORDS = 20, 0.5, 50
BROADCAST_ROWS = 100_000
#: Up to this many different repeated windows a lookup in the array is the cheaper way.
FEW = 24


def word_array(text: Column) -> Column:
    return F.filter(F.split(text, f"{SPACE}+"), lambda w: w != "")


def with_base_rules(docs: DataFrame, text: str = "text") -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and base_failed.

    Windows are compared by 64-bit hashes. Sorting the hashes shows the repeated ones; a
    text with few looks them up, one with many sorts (hash, place) pairs instead, so that
    a long text never costs the square of its length."""
    t = F.coalesce(F.col(text), F.lit(""))
    df = docs.withColumn("_t", t).withColumn("_w", word_array(F.col("_t"))).withColumn("_n", F.size("_w"))
    hashes = F.when(F.col("_n") < 4, F.array().cast("array<bigint>")).otherwise(F.transform(F.slice("_w", 1, F.greatest(F.col("_n") - 2, F.lit(0))), lambda w, i: F.xxhash64(w, F.get("_w", i + 1), F.get("_w", i + 2))))
    df = df.withColumn("_g", hashes).withColumn("_s", F.sort_array("_g"))
    again = F.array_distinct(F.filter("_s", lambda h, i: (i > 0) & (h == F.get("_s", i - 1))))
    df = df.withColumn("_d", again)
    places = F.filter(F.transform("_g", lambda h, i: F.when(F.array_contains("_d", h), i)), lambda i: i.isNotNull())
    pairs = F.sort_array(F.transform("_g", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    df = df.withColumn("_p", F.when(F.size("_d") > FEW, pairs))
    same = lambda a, b: a["h"] == b["h"]
    many = F.transform(F.filter("_p", lambda x, i: F.coalesce((i > 0) & same(x, F.get("_p", i - 1)), F.lit(False)) | F.coalesce(same(x, F.get("_p", i + 1)), F.lit(False))), lambda x: x["i"])
    df = df.withColumn("_at", F.when(F.size("_d") == 0, F.array().cast("array<int>")).when(F.size("_d") > FEW, many).otherwise(places))
    cover = F.size(F.array_distinct(F.flatten(F.transform("_at", lambda i: F.array(i, i + 1, i + 2)))))
    lines = F.filter(F.split("_t", "\n", -1), lambda x: x.rlike("[^\\x20\\x09-\\x0D]"))
    df = df.withColumn("_l", lines)
    n, rep = F.col("_n").cast("long"), F.when(F.size("_at") == 0, F.lit(0)).otherwise(cover).cast("long")
    df = df.select(*docs.columns, n.alias("n_words"), F.char_length(F.array_join("_w", "")).cast("long").alias("word_chars"), (F.char_length("_t") - F.char_length(F.regexp_replace("_t", SYMBOLS, ""))).cast("long").alias("n_symbols"), (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"), rep.alias("n_repeat_words"))
    return df.withColumn("base_failed", (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words")))


def normalised(text: Column) -> Column:
    """The whole text at once: lower case, digits as 0, runs of blanks as one; lines stay."""
    digits = F.when(text.rlike("[1-9]"), F.regexp_replace(F.lower(text), "[1-9]", "0")).otherwise(F.lower(text))
    return F.regexp_replace(digits, "[\\x20\\x09\\x0B-\\x0D]{2,}|[\\x09\\x0B-\\x0D]", " ")


def line_hashes(docs: DataFrame, host: str, text: str) -> DataFrame:
    """Adds _lines: (hash with host, word characters) of each line."""
    t = F.coalesce(F.col(text), F.lit(""))
    rows = F.filter(F.transform(F.split(normalised(t), "\n", -1), lambda x: F.trim(x)), lambda x: x != "")
    return docs.withColumn("_lines", F.transform(rows, lambda x: F.struct(F.xxhash64(F.col(host), x).alias("k"), F.char_length(F.replace(x, F.lit(" "), F.lit(""))).alias("c"))))


def frequent_lines(hashed: DataFrame, key: str, max_docs: int = MAX_DOCS) -> DataFrame:
    """k: lines that more than max_docs documents of a host hold."""
    pairs = hashed.select(F.xxhash64(key).alias("_h"), F.explode(F.array_distinct(F.transform("_lines", lambda x: x["k"]))).alias("k"))
    once = pairs.groupBy("k", "_h").agg(F.lit(1).alias("one"))
    return once.groupBy("k").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > max_docs).select("k")


def judge(docs: DataFrame, key: str = "doc_id", host: str = "source", text: str = "text", max_docs: int = MAX_DOCS, min_kept: float = MIN_KEPT, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Base counts, word characters in boilerplate lines and the verdict."""
    docs = picked(docs, _id=key, _host=host, _text=text)
    base = with_base_rules(docs.select("_id", "_text"), "_text").drop("_text")
    hashed = line_hashes(docs, "_host", "_text")
    common = checkpointed(frequent_lines(hashed, "_id", max_docs))
    lines = hashed.select(F.col("_id").alias("_key"), F.posexplode("_lines").alias("i", "x")).select("_key", "i", "x.k", "x.c")
    goal = F.broadcast(common) if common.count() <= broadcast_rows else common
    hits = lines.join(goal, "k").groupBy("_key").agg(F.collect_set(F.struct("i", "c")).alias("a"))  # lines of one document; a repeated row adds none
    hits = hits.select("_key", F.aggregate("a", F.lit(0).cast("long"), lambda s, x: s + x["c"]).alias("c"))
    out = base.join(hits, F.col("_id").eqNullSafe(F.col("_key")), "left").drop("_key")
    gone = F.coalesce(F.col("c"), F.lit(0).cast("long"))
    out = out.withColumn("boilerplate_chars", gone).drop("c")
    # one comparison over both: split in two, a filter on it would move below the base
    # rules' projections and repeat their expressions
    depleted = F.col("boilerplate_chars") > (1 - min_kept) * F.col("word_chars")
    return out.withColumn("kept", F.col("base_failed").cast("int") + depleted.cast("int") == 0).withColumnRenamed("_id", key)


def cleaned(docs: DataFrame, key: str = "doc_id", host: str = "source", text: str = "text", max_docs: int = MAX_DOCS, min_kept: float = MIN_KEPT) -> DataFrame:
    """The documents that stay, without their boilerplate lines: for callers that filter."""
    verdict = checkpointed(judge(docs, key, host, text, max_docs, min_kept)).where("kept").select(F.col(f"`{key}`").alias("_ok")).distinct()
    rows = boxed(docs, _id=key, _host=host, _text=text)
    common = checkpointed(frequent_lines(line_hashes(rows.drop("box"), "_host", "_text"), "_id", max_docs))
    flat = rows.where("_text IS NOT NULL").dropDuplicates(["_id"]).select("_id", "_host", F.posexplode(F.split("_text", "\n", -1)).alias("i", "line"))
    flat = flat.withColumn("k", F.xxhash64(F.col("_host"), F.trim(normalised(F.col("line")))))
    stay = flat.join(common.withColumn("_bad", F.lit(True)), "k", "left").where(F.col("_bad").isNull() | ~F.col("line").rlike("[^\\x20\\x09-\\x0D]"))
    whole = stay.groupBy(F.col("_id").alias("_key")).agg(F.sort_array(F.collect_list(F.struct("i", "line"))).alias("a")).select("_key", F.array_join(F.transform("a", lambda x: x["line"]), "\n").alias("_new"))
    out = rows.join(verdict, F.col("_id").eqNullSafe(F.col("_ok"))).join(whole, F.col("_id").eqNullSafe(F.col("_key")), "left")
    return unboxed(out, docs.columns, **{docs.columns[position(docs, text)]: F.coalesce("_new", F.lit(""))})


def op10_line_rules(spark, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents"))
