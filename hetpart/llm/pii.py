"""Personal data and what reveals it, in DataFrame functions only.

Base kinds are found by patterns whose failing matches are dropped. The patterns here
match what the plain ones do, written so that Java's engine takes linear time and no
deep recursion: possessive repeats, and no start inside a run that was tried already.

Beyond them, terms that reveal an entity are found from the corpus. An entity is the
value of a base match. For each, the words near it (``NEAR`` on a side, whatever stands
between; a hyphenated word is one) are counted by documents, and all words of all documents as well. A term t discloses an entity e if
their pointwise mutual information, ln(N n(e,t) / (n(e) n(t))), is at least the entity's
information ln(N / n(e)) over ``ALPHA``, on ``SUPPORT`` documents or more. It is then
generalised to its first letters, if the class of words with these letters discloses e
no longer, and removed otherwise. The words near an entity only tell which terms disclose
it: such a term goes wherever it stands in the documents that hold the entity.

Only 8-byte hashes are counted, combined before each shuffle; texts don't move for the
counts, and pairs of entity and term are bounded by the entity's occurrences.

Defined results: null and empty texts have no span; a null key is a key; repeated rows
count as documents each and give a row each (rows with one key must have one text);
overlapping base spans are all listed, and masked as one; extra columns are kept where
texts are rewritten.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import boxed, checkpointed, picked, position, table, unboxed

#: The kinds in order with their patterns.
EMAIL = "(?:(?<![A-Za-z0-9._%+-])|\\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\\.[A-Za-z0-9-]++)++"
IP = "(?:(?<![0-9])|\\G)[0-9]++(?:\\.[0-9]++){3}"
CARD = "[0-9](?:[\\x20-]?[0-9])++"
PHONE = "\\+[0-9][\\x20().0-9-]+[0-9]"
BYTE = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
#: A word, with inner hyphens; single letters and pairs only within a hyphenated one.
WORD = "\\p{L}{3,}+(?:-\\p{L}++)*+|\\p{L}{1,2}+(?:-\\p{L}++)++"
#: A word that is no part of an address, a number or an identifier.
TERM = f"(?<![\\p{{L}}@._%+0-9])(?<![\\p{{L}}@._%+0-9]-)(?:{WORD})(?!-?[\\p{{L}}@_%+0-9])(?!-?\\.[A-Za-z0-9])"
#: Words outside addresses: an address is one match, which its @ tells.
PLAIN = f"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\\.[A-Za-z0-9-]++)++|{WORD}"

NEAR, HEAD = 5, 4
ALPHA, SUPPORT = 1.1, 2
SPAN = "array<struct<s:int,e:int,hit:string>>"
#: Matches placed in one fold: a fold copies its list at each step, so long texts take blocks.
BLOCK = 256
#: Code points of the pieces that long texts are cut into before they are put together anew.
PIECE = 1024
MARKS = "array<struct<s:int,e:int,put:string>>"


def located(text: Column, pattern: str) -> Column:
    """(s, e, hit) of the matches: their places follow from the lengths of what is between.
    They are placed within blocks, then the blocks behind each other."""
    hits, gaps = F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), F.split(text, pattern, -1)
    zero = F.struct(F.lit(0).alias("pos"), F.array().cast(SPAN).alias("out"))
    none = F.struct(F.lit(0).alias("pos"), F.array().cast(f"array<{SPAN}>").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        s = acc["pos"] + F.char_length(x["gap"])
        e = s + F.char_length(x["hit"])
        return F.struct(e.alias("pos"), F.concat(acc["out"], F.array(F.struct(s.alias("s"), e.alias("e"), x["hit"].alias("hit")))).alias("out"))

    def behind(acc: Column, block: Column) -> Column:
        moved = F.transform(block["out"], lambda x: F.struct((acc["pos"] + x["s"]).alias("s"), (acc["pos"] + x["e"]).alias("e"), x["hit"].alias("hit")))
        return F.struct((acc["pos"] + block["pos"]).alias("pos"), F.concat(acc["out"], F.array(moved)).alias("out"))

    def placed(pairs: Column) -> Column:
        starts = F.sequence(F.lit(1), F.greatest(F.size(pairs), F.lit(1)), F.lit(BLOCK))
        blocks = F.transform(starts, lambda k: F.aggregate(F.slice(pairs, k, F.lit(BLOCK)), zero, step))
        return F.flatten(F.aggregate(blocks, none, behind, lambda acc: acc["out"]))

    pairs = F.zip_with(F.slice(gaps, 1, F.size(hits)), hits, lambda g, h: F.struct(g.alias("gap"), h.alias("hit")))
    return F.get(F.transform(F.array(pairs), placed), F.lit(0))  # an array of one: the matches are found once


def luhn(digits: Column) -> Column:
    def value(c: Column, i: Column) -> Column:
        d = F.ascii(c) - 48
        return F.when(i % 2 == 0, d).otherwise(F.when(d > 4, 2 * d - 9).otherwise(2 * d))

    return F.aggregate(F.transform(F.split(F.reverse(digits), ""), value), F.lit(0), lambda a, x: a + x) % 10 == 0


def _card(hit: Column) -> Column:
    digits = F.translate(hit, " -", "")
    return F.when(F.char_length(digits).between(13, 19), luhn(digits)).otherwise(F.lit(False))


KINDS = (
    ("email", EMAIL, lambda t: F.contains(t, F.lit("@")), lambda h: F.lit(True), lambda h: F.lower(h)),
    ("ip", IP, lambda t: t.rlike("[0-9]\\.[0-9]"), lambda h: h.rlike(f"^{BYTE}(?:\\.{BYTE}){{3}}$"), lambda h: h),
    ("card", CARD, lambda t: t.rlike("[0-9][\\x20-]?[0-9][\\x20-]?[0-9]"), _card, lambda h: F.translate(h, " -", "")),
    ("phone", PHONE, lambda t: F.contains(t, F.lit("+")), lambda h: F.char_length(F.regexp_replace(h, "[^0-9]", "")).between(9, 15), lambda h: F.regexp_replace(h, "[^0-9]", "")),
)


def _checked(valid):
    return lambda x: valid(x["hit"])


def _mask(kind: str):
    return lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), F.lit(f"[{kind.upper()}]").alias("put"))


def with_base_spans(docs: DataFrame, text: str = "text") -> DataFrame:
    """Adds _t (the text, never null) and, by kind, the valid spans _email, _ip, _card, _phone."""
    out = docs.withColumn("_t", F.coalesce(F.col(text), F.lit("")))
    for kind, pattern, maybe, valid, _ in KINDS:
        out = out.withColumn(f"_{kind}", F.when(maybe(F.col("_t")), F.filter(located(F.col("_t"), pattern), _checked(valid))).otherwise(F.array().cast(SPAN)))
    return out


def listed(kind: str, spans: Column) -> Column:
    return F.transform(spans, lambda x: F.concat_ws(":", F.lit(kind), x["s"].cast("string"), x["e"].cast("string")))


def _entities(kind: str, value):
    return lambda x: F.struct(F.xxhash64(F.lit(kind), value(x["hit"])).alias("entity"), x["s"].alias("s"), x["e"].alias("e"))


def with_words(spanned: DataFrame, key: str) -> DataFrame:
    """(key, _bases, _near, _words) of the documents with a base span: the spans with their
    entities, and the terms and all words outside addresses with their places."""
    bases = F.concat(*[F.transform(f"_{kind}", _entities(kind, value)) for kind, _, _, _, value in KINDS])
    words = F.filter(located(F.col("_t"), PLAIN), lambda x: ~F.contains(x["hit"], F.lit("@")))
    some = F.greatest(*[F.size(f"_{kind}") for kind, *_ in KINDS]) > 0
    return spanned.where(some).select(key, bases.alias("_bases"), located(F.col("_t"), TERM).alias("_near"), words.alias("_words"))


def _before(words: Column, edge: str, place: Column, *, at: bool) -> Column:
    """How many words have their edge before the place (or at it): they are in order, so
    halving finds it in 31 steps."""
    def step(acc: Column, _: Column) -> Column:
        middle = F.shiftright(acc["lo"] + acc["hi"], 1)
        x = F.get(words, middle)[edge]
        below = (acc["lo"] < acc["hi"]) & (x <= place if at else x < place)
        return F.struct(F.when(below, middle + 1).otherwise(acc["lo"]).alias("lo"), F.when(below, acc["hi"]).otherwise(F.least(middle, acc["hi"])).alias("hi"))

    return F.aggregate(F.sequence(F.lit(1), F.lit(31)), F.struct(F.lit(0).alias("lo"), F.size(words).alias("hi")), step, lambda acc: acc["lo"])


def near_terms(found: DataFrame, key: str) -> DataFrame:
    """Rows (key, entity, term): the NEAR terms on each side of each base span."""
    def terms(x: Column) -> Column:
        n = _before(F.col("_near"), "e", x["s"], at=True)
        left = F.slice("_near", F.greatest(n - (NEAR - 1), F.lit(1)), F.least(n, F.lit(NEAR)))
        right = F.slice("_near", _before(F.col("_near"), "s", x["e"], at=False) + 1, F.lit(NEAR))
        return F.struct(x["entity"].alias("entity"), F.array_distinct(F.transform(F.concat(left, right), lambda y: F.lower(y["hit"]))).alias("terms"))

    rows = found.select(key, F.explode(F.transform("_bases", terms)).alias("x"))
    # an entity without a term near it counts as well: a row with a null term
    return rows.select(key, "x.entity", F.explode_outer("x.terms").alias("term"))


def _hashed(x: Column) -> Column:
    """A word, and the parts of a hyphenated one, with the place of the whole."""
    def part(acc: Column, w: Column) -> Column:
        e = acc["pos"] + F.char_length(w)
        return F.struct((e + 1).alias("pos"), F.concat(acc["out"], F.array(F.struct(F.xxhash64(F.lower(w)).alias("h"), acc["pos"].alias("s"), e.alias("e"), x["s"].alias("of"), x["e"].alias("to")))).alias("out"))

    whole = F.array(F.struct(F.xxhash64(F.lower(x["hit"])).alias("h"), x["s"].alias("s"), x["e"].alias("e"), x["s"].alias("of"), x["e"].alias("to")))
    zero = F.struct(x["s"].alias("pos"), F.array().cast("array<struct<h:bigint,s:int,e:int,of:int,to:int>>").alias("out"))
    return F.when(F.contains(x["hit"], F.lit("-")), F.concat(whole, F.aggregate(F.split(x["hit"], "-"), zero, part, lambda acc: acc["out"]))).otherwise(whole)


def head(term: Column) -> Column:
    return F.substring(term, 1, HEAD)


def word_counts(docs: DataFrame, text: str = "text") -> DataFrame:
    """Documents with each word and with each word beginning, by 8-byte hash."""
    words = F.regexp_extract_all(F.lower(F.coalesce(F.col(text), F.lit(""))), F.lit(WORD), F.lit(0))
    different = docs.select(F.array_distinct(words).alias("w"))
    hashes = F.concat(F.transform("w", lambda w: F.xxhash64(w)), F.array_distinct(F.transform("w", lambda w: F.xxhash64(F.lit("head"), head(w)))))
    return different.select(F.explode(hashes).alias("h")).groupBy("h").agg(F.count(F.lit(1)).alias("n"))


def disclosing(near: DataFrame, counts: DataFrame, total: int, key: str, alpha: float = ALPHA, support: int = SUPPORT) -> DataFrame:
    """(entity, term, generalise): the terms over the threshold of disclosure."""
    entities = near.select(key, "entity").distinct().groupBy("entity").agg(F.count(F.lit(1)).alias("n_e"))
    pairs = near.where("term IS NOT NULL").select(key, "entity", "term").distinct()
    both = pairs.groupBy("entity", "term").agg(F.count(F.lit(1)).alias("n_et"))
    wide = pairs.select(key, "entity", head(F.col("term")).alias("head")).distinct().groupBy("entity", "head").agg(F.count(F.lit(1)).alias("n_eg"))
    n = F.lit(float(max(total, 1)))
    bits = lambda joint, e, t: F.ln(n * joint / (e * t))
    over = lambda joint, t: (joint >= support) & (bits(joint, F.col("n_e"), t) >= F.ln(n / F.col("n_e")) / alpha) & (F.col("n_e") < n)
    df = both.where(F.col("n_et") >= support).join(entities, "entity").withColumn("h", F.xxhash64("term")).join(counts, "h").withColumnRenamed("n", "n_t").drop("h")
    df = df.where(over(F.col("n_et"), F.col("n_t"))).withColumn("head", head(F.col("term")))
    df = df.join(wide, ["entity", "head"]).withColumn("h", F.xxhash64(F.lit("head"), F.col("head"))).join(counts, "h")
    return df.select("entity", "term", (~over(F.col("n_eg"), F.col("n"))).alias("generalise"))


def term_spans(docs: DataFrame, key: str = "doc_id", text: str = "text", alpha: float = ALPHA, support: int = SUPPORT) -> DataFrame:
    """_key and _terms: the sorted spans of disclosing terms of each document that has one."""
    words = checkpointed(with_words(with_base_spans(docs, text), key))
    near = checkpointed(near_terms(words, key))
    total = docs.count()
    told = checkpointed(disclosing(near, word_counts(docs, text), total, key, alpha, support).withColumn("h", F.xxhash64("term")).select("entity", "h", "generalise"))
    # every place of a told term in the documents that hold its entity, not only the near ones
    places = words.select(key, F.explode(F.flatten(F.transform("_words", _hashed))).alias("x")).select(key, "x.*").join(told.select("h").distinct(), "h", "left_semi")
    places = places.groupBy(key, "h").agg(F.collect_set(F.struct("s", "e", "of", "to")).alias("at"))
    holds = near.select(F.col(key).alias("_key"), "entity").distinct()
    found = places.join(holds, F.col(key).eqNullSafe(F.col("_key"))).join(told, ["entity", "h"])
    # a term that discloses several entities is generalised only if it may be for all
    one = found.groupBy("_key", "h").agg(F.min("generalise").alias("generalise"), F.first("at").alias("at"))
    one = one.select("_key", "generalise", F.explode("at").alias("x")).select("_key", "generalise", "x.*")
    # of a hyphenated word and its parts the whole is listed, if it is told
    one = one.groupBy("_key", "of", "to").agg(F.min("generalise").alias("least"), F.sort_array(F.collect_set(F.struct("s", "e", "generalise"))).alias("at"))
    whole = F.exists("at", lambda x: (x["s"] == F.col("of")) & (x["e"] == F.col("to")))
    one = one.select("_key", F.when(whole, F.array(F.struct(F.col("of").alias("s"), F.col("to").alias("e"), F.col("least").alias("generalise")))).otherwise(F.col("at")).alias("at"))
    return one.groupBy("_key").agg(F.sort_array(F.flatten(F.collect_list("at"))).alias("_terms"))


def findings(docs: DataFrame, key: str = "doc_id", text: str = "text", **limits) -> DataFrame:
    """Counts and span lists of each document. Texts stay where they are read."""
    name, docs, key, text = key, picked(docs, _id=key, _text=text), "_id", "_text"
    base = with_base_spans(docs, text)
    lists = F.concat(*[listed(kind, F.col(f"_{kind}")) for kind, *_ in KINDS])
    base = base.select(key, *[F.size(f"_{kind}").cast("long").alias(f"n_{kind}") for kind, *_ in KINDS], lists.alias("_list"))
    out = base.join(term_spans(docs, key, text, **limits), F.col(key).eqNullSafe(F.col("_key")), "left")
    terms = F.coalesce("_terms", F.array().cast("array<struct<s:int,e:int,generalise:boolean>>"))
    return out.select(F.col("_id").alias(name), *[f"n_{kind}" for kind, *_ in KINDS], F.sha2(F.array_join("_list", ",").cast("binary"), 256).alias("base_sha256"), F.array_join(F.concat("_list", listed("term", terms)), ",").alias("spans"), F.size(terms).cast("long").alias("n_term"))


def reached(marks: Column) -> Column:
    """Adds ``before`` to sorted marks: how far the marks before it reach. As places in
    ``located``, it is found within blocks first, then from block to block."""
    kind = "array<struct<s:int,e:int,put:string,before:int>>"
    zero = F.struct(F.lit(0).alias("to"), F.array().cast(kind).alias("out"))
    none = F.struct(F.lit(0).alias("to"), F.array().cast(f"array<{kind}>").alias("out"))
    mark = lambda x, before: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["put"].alias("put"), before.alias("before"))

    def step(acc: Column, x: Column) -> Column:
        return F.struct(F.greatest(acc["to"], x["e"]).alias("to"), F.concat(acc["out"], F.array(mark(x, acc["to"]))).alias("out"))

    def behind(acc: Column, block: Column) -> Column:
        moved = F.transform(block["out"], lambda x: mark(x, F.greatest(acc["to"], x["before"])))
        return F.struct(F.greatest(acc["to"], block["to"]).alias("to"), F.concat(acc["out"], F.array(moved)).alias("out"))

    def told(all_: Column) -> Column:
        starts = F.sequence(F.lit(1), F.greatest(F.size(all_), F.lit(1)), F.lit(BLOCK))
        blocks = F.transform(starts, lambda k: F.aggregate(F.slice(all_, k, F.lit(BLOCK)), zero, step))
        return F.flatten(F.aggregate(blocks, none, behind, lambda acc: acc["out"]))

    return F.get(F.transform(F.array(marks), told), F.lit(0))


def cut(a: Column, b: Column) -> Column:
    """The text from place a to place b, out of the pieces in ``_pieces``: a place is reached
    within its piece, not from the text's start."""
    first, last = F.floor(a / PIECE).cast("int"), F.floor((b - 1) / PIECE).cast("int")
    head = F.substring(F.get("_pieces", first), a - first * PIECE + 1, F.least(b - a, F.lit(PIECE)))
    tail = F.substring(F.get("_pieces", last), F.lit(1), b - last * PIECE)
    inner = F.when(last - first > 1, F.array_join(F.slice("_pieces", first + 2, F.greatest(last - first - 1, F.lit(0))), "")).otherwise("")
    return F.when(a >= b, "").when(first == last, head).otherwise(F.concat(head, inner, tail))


def sanitised(docs: DataFrame, key: str = "doc_id", text: str = "text", **limits) -> DataFrame:
    """The documents with base spans masked and disclosing terms generalised or removed."""
    # extra columns travel in one struct, so their names can't clash with those here
    rows = boxed(docs, _id=key, _text=text)
    terms = term_spans(rows.select("_id", "_text"), "_id", "_text", **limits)
    df = with_base_spans(rows.join(terms, F.col("_id").eqNullSafe(F.col("_key")), "left").drop("_key"), "_text")
    marks = [F.transform(f"_{k}", _mask(k)) for k, *_ in KINDS]
    # an empty put stands for the first letters
    words = F.transform(F.coalesce("_terms", F.array().cast("array<struct<s:int,e:int,generalise:boolean>>")), lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), F.when(x["generalise"], F.lit("")).otherwise(F.lit("[TERM]")).alias("put")))
    df = df.withColumn("_marks", reached(F.sort_array(F.concat(*marks, words).cast(MARKS))))
    df = df.withColumn("_pieces", F.when(F.size("_marks") > 0, F.regexp_extract_all("_t", F.lit(f"(?s).{{1,{PIECE}}}"), F.lit(0))))
    apart = F.filter("_marks", lambda x: x["s"] >= x["before"])
    put = lambda x: F.when(x["put"] == "", F.concat(cut(x["s"], x["s"] + HEAD), F.lit("*"))).otherwise(x["put"])
    end = F.array_max(F.transform("_marks", lambda x: x["e"]))
    done = F.concat(F.array_join(F.flatten(F.transform(apart, lambda x: F.array(cut(x["before"], x["s"]), put(x)))), ""), cut(end, F.char_length("_t")))
    new = F.when(F.size("_marks") == 0, F.col("_text")).otherwise(done)
    return unboxed(df.select("box", new.alias("_new")), docs.columns, **{docs.columns[position(docs, text)]: F.col("_new")})


def op3_pii(spark, sf_dir: str) -> DataFrame:
    return findings(table(spark, sf_dir, "documents"))
