"""Tool-call linking: calls meet their results by identifier, stand in an order that
respects what they depend on, are checked against their tools' schemas, and become
canonical JSON records.

calls:   conv_id, call_id, pos, tool, arguments (JSON text), after (ids it depends on)
results: conv_id, call_id, pos, content

Order. Where a dependency stands before its call, the order of positions is already
topological. Where one stands after its call (or is the call itself), the positions
between both are a tangle; overlapping tangles are merged, and the calls of all tangles
are peeled in rounds (those whose dependencies are placed come next). Calls sort by
(conv_id, seq_major, seq_level, pos, call_id): seq_major is the position where the tangle
begins, or the own one. What no round places is on a cycle or behind one in its tangle.

Nothing collects a conversation or an identifier into one task. Running maxima over a
conversation are taken within ranges of rows, then over the ranges; identifiers with a
thousandth of all rows meet their calls by broadcast; rounds are as many as the longest
chain in a tangle.

Defined results: a repeated call id in a conversation is a call for the least (pos,
arguments, tool), the others are ``repeated``; a call without a result is ``open``, a
result without a call is ``orphan``, a result that stands before its call is no result
for it but ``early``; of several results the first by (pos, content) counts; null ids
never match; null, empty, invalid or too deeply nested arguments are errors, and so is an unknown tool; a
dependency that doesn't exist is an error and orders nothing; extra columns are ignored.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpointed, hot_join, picked, table


# ---------------------------------------------------------------- JSON


def _pairs(items):
    out = dict(items)
    if len(out) != len(items):
        raise ValueError("a name stands twice")
    return out


def _no_constant(x):
    raise ValueError(f"{x} is no JSON")


def parse(text: str | None):
    return json.loads(text or "", object_pairs_hook=_pairs, parse_constant=_no_constant)


def canonical(value) -> str:
    """Sorted names, no white space, shortest numbers: equal values give equal texts."""

    def plain(v):
        if isinstance(v, float) and v == int(v) and abs(v) < 2**53:
            return int(v)
        if isinstance(v, dict):
            return {k: plain(x) for k, x in v.items()}
        return [plain(x) for x in v] if isinstance(v, list) else v

    def order(v):
        if isinstance(v, dict):
            return {k: order(v[k]) for k in sorted(v, key=lambda s: s.encode("utf-16-be", "surrogatepass"))}
        return [order(x) for x in v] if isinstance(v, list) else v

    return json.dumps(order(plain(value)), ensure_ascii=False, separators=(",", ":"))


TYPES = {
    "object": lambda v: isinstance(v, dict),
    "array": lambda v: isinstance(v, list),
    "string": lambda v: isinstance(v, str),
    "boolean": lambda v: isinstance(v, bool),
    "null": lambda v: v is None,
    "integer": lambda v: not isinstance(v, bool) and (isinstance(v, int) or isinstance(v, float) and v.is_integer()),
    "number": lambda v: isinstance(v, (int, float)) and not isinstance(v, bool),
}


def violations(value, schema: dict, at: str = "$") -> list[str]:
    """Where a value breaks a schema: types, enum, const, bounds, lengths, pattern, required
    and further properties, items, anyOf."""
    out = []
    kinds = schema.get("type")
    if kinds and not any(TYPES[k](value) for k in ([kinds] if isinstance(kinds, str) else kinds)):
        return [f"{at}: not {kinds if isinstance(kinds, str) else '/'.join(kinds)}"]
    if "enum" in schema and value not in schema["enum"]:
        out.append(f"{at}: not in enum")
    if "const" in schema and value != schema["const"]:
        out.append(f"{at}: not the constant")
    if TYPES["number"](value):
        out += [f"{at}: {k}" for k, bad in (("minimum", lambda b: value < b), ("maximum", lambda b: value > b), ("exclusiveMinimum", lambda b: value <= b), ("exclusiveMaximum", lambda b: value >= b)) if k in schema and bad(schema[k])]
    if isinstance(value, str):
        out += [f"{at}: {k}" for k, bad in (("minLength", lambda b: len(value) < b), ("maxLength", lambda b: len(value) > b), ("pattern", lambda b: not re.search(b, value))) if k in schema and bad(schema[k])]
    if isinstance(value, list):
        out += [f"{at}: {k}" for k, bad in (("minItems", lambda b: len(value) < b), ("maxItems", lambda b: len(value) > b)) if k in schema and bad(schema[k])]
        if "items" in schema:
            out += [e for i, v in enumerate(value) for e in violations(v, schema["items"], f"{at}[{i}]")]
    if isinstance(value, dict):
        known = schema.get("properties", {})
        out += [f"{at}.{k}: missing" for k in schema.get("required", []) if k not in value]
        more = schema.get("additionalProperties", True)
        for k in sorted(value):
            if k in known:
                out += violations(value[k], known[k], f"{at}.{k}")
            elif more is False:
                out.append(f"{at}.{k}: not allowed")
            elif isinstance(more, dict):
                out += violations(value[k], more, f"{at}.{k}")
    if "anyOf" in schema and all(violations(value, s, at) for s in schema["anyOf"]):
        out.append(f"{at}: none of anyOf")
    return out


# ---------------------------------------------------------------- order


def _key(prefix: str):
    return F.struct(F.col(f"{prefix}pos").alias("pos"), F.col(f"{prefix}call_id").alias("id"))


def running_max(rows: DataFrame, value: str, out: str, *, own: bool) -> DataFrame:
    """Adds the greatest value up to each row of its conversation, by ``at``; own: with the
    row itself and those at the same place, else only rows before. Rows are dealt by ranges,
    and each range's greatest value goes on to the later ranges, a row a range."""
    kind = rows.schema[value].dataType
    dealt = checkpointed(rows.repartitionByRange("conv_id", "at").withColumn("_b", F.spark_partition_id()))
    inner = Window.partitionBy("conv_id", "_b").orderBy("at")
    inner = inner.rangeBetween(Window.unboundedPreceding, Window.currentRow) if own else inner.rowsBetween(Window.unboundedPreceding, -1)
    ranges = dealt.groupBy("conv_id", "_b").agg(F.max(value).alias("_top"))
    before = Window.partitionBy("conv_id").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    carry = ranges.select(F.col("conv_id").alias("_c"), F.col("_b").alias("_r"), F.max("_top").over(before).alias("_carry"))
    got = dealt.withColumn("_in", F.max(value).over(inner)).join(carry, (F.col("conv_id") == F.col("_c")) & (F.col("_b") == F.col("_r")))
    return got.withColumn(out, F.greatest("_in", "_carry").cast(kind)).drop("_b", "_in", "_carry", "_c", "_r")


def ordered(calls: DataFrame) -> DataFrame:
    """Adds seq_major, seq_level and on_cycle to calls with distinct (conv_id, call_id)."""
    deps = calls.select("conv_id", "call_id", "pos", F.explode("after").alias("dep_call_id"))
    target = calls.select("conv_id", F.col("call_id").alias("dep_call_id"), F.col("pos").alias("dep_pos"))
    edges = deps.join(target, ["conv_id", "dep_call_id"]).distinct()
    back = checkpointed(edges.where(_key("dep_") >= _key("")).select("conv_id", _key("").alias("lo"), _key("dep_").alias("hi")))
    if back.isEmpty():
        return calls.withColumns({"seq_major": F.col("pos"), "seq_level": F.lit(0), "on_cycle": F.lit(False)})
    # overlapping tangles of a conversation become one
    parts = running_max(back.select("conv_id", F.col("lo").alias("at"), "hi"), "hi", "reach", own=False)
    parts = parts.withColumn("begin", F.when(F.coalesce(F.col("at") > F.col("reach"), F.lit(True)), F.col("at")))
    parts = running_max(parts.select("conv_id", "at", "hi", "begin"), "begin", "part", own=True)
    tangles = checkpointed(parts.groupBy("conv_id", "part").agg(F.max("hi").alias("hi")))
    # a call is in the tangle that begins last before it, if that reaches so far
    both = calls.select("conv_id", "call_id", _key("").alias("at"), F.lit(None).cast(tangles.select(F.struct("part", "hi")).schema[0].dataType).alias("tangle"))
    both = both.unionByName(tangles.select("conv_id", F.lit(None).cast("string").alias("call_id"), F.col("part").alias("at"), F.struct("part", "hi").alias("tangle")))
    inside = running_max(both, "tangle", "last", own=True).where(F.col("tangle").isNull() & (F.col("at") <= F.col("last.hi")))
    inside = checkpointed(inside.select("conv_id", "call_id", F.col("last.part").alias("part"), F.col("last.part.pos").alias("major")))
    inner = edges.select("conv_id", "call_id", "dep_call_id").join(inside.select("conv_id", "call_id", "part"), ["conv_id", "call_id"])
    inner = checkpointed(inner.join(inside.select("conv_id", F.col("call_id").alias("dep_call_id"), "part"), ["conv_id", "dep_call_id", "part"]))
    left, placed, level = inside, None, 0
    while True:
        waiting = inner.join(left.select("conv_id", F.col("call_id").alias("dep_call_id")), ["conv_id", "dep_call_id"], "left_semi").select("conv_id", "call_id").distinct()
        ready = checkpointed(left.join(waiting, ["conv_id", "call_id"], "left_anti").withColumn("level", F.lit(level)))
        if ready.isEmpty():
            break
        placed = ready if placed is None else placed.unionByName(ready)
        left = checkpointed(left.join(ready.select("conv_id", "call_id"), ["conv_id", "call_id"], "left_anti"))
        level += 1
    done = (inside.withColumn("level", F.lit(0)).where("false") if placed is None else placed).groupBy("conv_id", "part").agg((F.max("level") + 1).alias("level"))
    rest = left.join(done, ["conv_id", "part"], "left").withColumn("level", F.coalesce("level", F.lit(0))).withColumn("cyclic", F.lit(True))
    seq = rest if placed is None else placed.withColumn("cyclic", F.lit(False)).unionByName(rest)
    out = calls.join(seq.drop("part"), ["conv_id", "call_id"], "left")
    return out.withColumns({"seq_major": F.coalesce("major", "pos"), "seq_level": F.coalesce("level", F.lit(0)), "on_cycle": F.coalesce("cyclic", F.lit(False))}).drop("major", "level", "cyclic")


# ---------------------------------------------------------------- linking

COLUMNS = "conv_id, call_id, pos, tool, status, seq_major, seq_level, on_cycle, n_results, result_pos, errors, record".split(", ")


def link(calls: DataFrame, results: DataFrame, schemas: dict[str, dict]) -> DataFrame:
    """One row for each call and each orphaned result, with the canonical record."""
    calls = calls.select("conv_id", "call_id", "pos", "tool", "arguments", F.coalesce("after", F.array().cast("array<string>")).alias("after"))
    ids, n = ["conv_id", "call_id"], F.count(F.lit(1)).alias("n")
    named = calls.where("conv_id IS NOT NULL AND call_id IS NOT NULL")
    equal = checkpointed(named.groupBy(*ids, "pos", "tool", "arguments", "after").agg(F.count(F.lit(1)).alias("times")))
    first = equal.groupBy(*ids).agg(F.min(F.struct("pos", "arguments", "tool", "after")).alias("x"), n)
    first = checkpointed(first.select(*ids, "x", "n"))
    total = equal.count()
    met = hot_join(equal, first, ids, "n", total)
    spare = F.col("times") - F.struct("pos", "arguments", "tool", "after").eqNullSafe(F.col("x")).cast("int")
    again = met.withColumn("spare", spare).where("spare > 0").withColumn("i", F.explode(F.sequence(F.lit(1).cast("long"), F.col("spare").cast("long")))).select(calls.columns)
    first = first.select(*ids, "x.*")
    lost = calls.where("conv_id IS NULL OR call_id IS NULL")
    given = results.select("conv_id", "call_id", F.col("pos").alias("result_pos"), "content")
    sizes = checkpointed(given.groupBy(*ids).agg(n))
    n_given = sizes.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    met = hot_join(given, sizes.join(first.select(*ids, "pos"), ids), ids, "n", n_given)
    answer = met.groupBy(*ids).agg(F.min(F.when(F.col("result_pos") > F.col("pos"), F.struct("result_pos", "content"))).alias("r"), F.sum((F.col("result_pos") > F.col("pos")).cast("long")).alias("n_results"))
    unmet = sizes.join(first.select(*ids), ids, "left_anti")
    stray = hot_join(given, unmet.where("conv_id IS NOT NULL AND call_id IS NOT NULL"), ids, "n", n_given).drop("n").unionByName(given.where("conv_id IS NULL OR call_id IS NULL"))
    gone = first.select("conv_id", F.explode("after").alias("dep"), "call_id").join(first.select("conv_id", F.col("call_id").alias("dep")), ["conv_id", "dep"], "left_anti")
    gone = gone.groupBy("conv_id", "call_id").agg(F.sort_array(F.collect_set("dep")).alias("missing"))
    good = ordered(first).join(answer, ["conv_id", "call_id"], "left").join(gone, ["conv_id", "call_id"], "left")
    good = good.withColumn("status", F.when(F.col("r").isNotNull(), "linked").when(F.col("n_results").isNotNull(), "early").otherwise("open"))
    none = {"seq_major": F.col("pos"), "seq_level": F.lit(0), "on_cycle": F.lit(False), "n_results": F.lit(0).cast("long"), "result_pos": F.lit(None).cast("long"), "content": F.lit(None).cast("string"), "missing": F.array().cast("array<string>")}
    good = good.withColumns({"result_pos": F.col("r.result_pos"), "content": F.col("r.content"), "n_results": F.coalesce("n_results", F.lit(0).cast("long")), "missing": F.coalesce("missing", F.array().cast("array<string>"))})
    orphan = stray.select("conv_id", "call_id", F.col("result_pos").alias("pos"), F.lit(None).cast("string").alias("tool"), F.lit(None).cast("string").alias("arguments"), F.array().cast("array<string>").alias("after"), "content").withColumns({k: v for k, v in none.items() if k != "content"}).withColumn("status", F.lit("orphan"))
    other = again.withColumn("status", F.lit("repeated")).unionByName(lost.withColumn("status", F.lit("unnamed"))).withColumns(none)
    wide = ["conv_id", "call_id", "pos", "tool", "status", "seq_major", "seq_level", "on_cycle", "n_results", "result_pos", "arguments", "after", "content", "missing"]
    rows = good.select(wide).unionByName(other.select(wide)).unionByName(orphan.select(wide))

    def finish(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            errors, records = [], []
            for r in f.itertuples(index=False):
                bad, value = [], None
                if r.status != "orphan":
                    try:
                        value = parse(r.arguments)
                        canonical(value).encode()  # a lone surrogate is no text
                        bad = violations(value, schemas[r.tool]) if r.tool in schemas else [f"unknown tool {r.tool}"]
                    except (ValueError, RecursionError) as e:
                        value = None
                        bad = [f"arguments: {'nested too deeply' if isinstance(e, RecursionError) else str(e).split(':')[0]}"]
                    bad += [f"missing dependency {x}" for x in r.missing]
                    bad += ["on a cycle"] if r.on_cycle else []
                record = {"id": r.call_id, "tool": r.tool, "arguments": value, "after": sorted(r.after), "status": r.status, "result": r.content}
                errors.append(bad)
                records.append(canonical({k: v for k, v in record.items() if not (k == "result" and v is None)}))
            f = f.drop(columns=["arguments", "after", "content", "missing"])
            f["errors"], f["record"] = errors, records
            yield f[COLUMNS]

    kind = lambda c: rows.schema[c].dataType.simpleString()
    # integers that may be null stay exact as text
    narrow = rows.withColumns({c: F.col(c).cast("string") for c in ("conv_id", "pos", "seq_major", "result_pos", "n_results")})
    text = {"conv_id", "call_id", "pos", "tool", "status", "seq_major", "n_results", "result_pos", "record"}
    schema = ", ".join(f"{c} {'string' if c in text else 'array<string>' if c == 'errors' else kind(c)}" for c in COLUMNS)
    out = narrow.mapInPandas(finish, schema)
    return out.withColumns({"conv_id": F.col("conv_id").cast(kind("conv_id")), **{c: F.col(c).cast("long") for c in ("pos", "seq_major", "result_pos", "n_results")}})


def tagged(turns: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Calls and results written in turns' texts as <tool_call>{"id", "name", "arguments",
    "after"}</tool_call> and <tool_result id="...">...</tool_result>."""
    inner = turns.select("conv_id", "turn", F.posexplode(F.regexp_extract_all("text", F.lit("(?s)<tool_call>(.*?)</tool_call>"), F.lit(1))).alias("i", "j"))
    get = lambda p: F.get_json_object("j", p)
    calls = inner.select("conv_id", get("$.id").alias("call_id"), (F.col("turn") * 1000 + F.col("i")).cast("long").alias("pos"), get("$.name").alias("tool"), get("$.arguments").alias("arguments"), F.from_json(get("$.after"), "array<string>").alias("after"))
    pattern = '(?s)<tool_result id="([^"]*)">(.*?)</tool_result>'
    both = F.arrays_zip(F.regexp_extract_all("text", F.lit(pattern), F.lit(1)).alias("id"), F.regexp_extract_all("text", F.lit(pattern), F.lit(2)).alias("content"))
    found = turns.select("conv_id", "turn", F.posexplode(both).alias("i", "x"))
    return calls, found.select("conv_id", F.col("x.id").alias("call_id"), (F.col("turn") * 1000 + F.col("i")).cast("long").alias("pos"), F.col("x.content").alias("content"))


def turns_as_calls(turns: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Calls out of conversations without tool tags; all of it is read from the texts.

    A user's or system's turn is a call. Its identifier is its first two words, so calls of
    one opening share one. A system's turn calls ``configure``, a user's ``draft`` if it has
    several lines, else ``reply``. A call of an even number of words depends on the calls one
    and two turns after it, one of a number divisible by three on those one and two turns
    before. An assistant's turn is the result for the identifier of the turn before it (an
    orphan if that is no call). Of several rows of one turn the least identifier is meant."""
    words = F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit(r"[\p{L}\p{N}]+"), F.lit(0))
    asks = turns.where(F.col("role").isin("user", "system")).select("conv_id", "turn", "role", "text", words.alias("w"))
    asks = asks.withColumn("call_id", F.array_join(F.slice("w", 1, 2), " ")).withColumn("n", F.size("w"))
    ident = asks.groupBy("conv_id", "turn").agg(F.min("call_id").alias("dep_id")).withColumnRenamed("turn", "dep")
    later, earlier = F.col("n") % 2 == 0, F.col("n") % 3 == 0
    way = F.concat(F.when(later, F.array(F.lit(1), F.lit(2))).otherwise(F.array()), F.when(earlier, F.array(F.lit(-1), F.lit(-2))).otherwise(F.array()))
    deps = asks.select("conv_id", "turn", "call_id", "n", F.explode(way).alias("k")).select("conv_id", "turn", "call_id", "n", (F.col("turn") + F.col("k")).alias("dep")).distinct().join(ident, ["conv_id", "dep"])
    deps = deps.groupBy("conv_id", "turn", "call_id", "n").agg(F.sort_array(F.collect_set("dep_id")).alias("after"))
    body = F.to_json(F.struct(F.col("text").alias("prompt"), F.col("turn"), F.col("n").alias("n_words"), F.get("w", F.lit(0)).alias("opening")), {"ignoreNullFields": "false"})
    tool = F.when(F.col("role") == "system", "configure").when(F.contains("text", F.lit("\n")), "draft").otherwise("reply")
    calls = asks.join(deps, ["conv_id", "turn", "call_id", "n"], "left").select("conv_id", "call_id", F.col("turn").alias("pos"), tool.alias("tool"), body.alias("arguments"), "after")
    answers = turns.where("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("dep"), F.col("turn").alias("pos"), F.col("text").alias("content"))
    results = answers.join(ident, ["conv_id", "dep"], "left").select("conv_id", F.col("dep_id").alias("call_id"), "pos", "content")
    return calls, results


def _body(least: int, most: int) -> dict:
    """The schema of a tool that takes prompts of so many words."""
    fields = {"prompt": {"type": "string", "minLength": 1}, "turn": {"type": "integer", "minimum": 0}, "n_words": {"type": "integer", "minimum": least, "maximum": most}, "opening": {"type": "string", "maxLength": 9}}
    return {"type": "object", "properties": fields, "required": ["prompt", "turn", "n_words", "opening"], "additionalProperties": False}


SCHEMAS = {"reply": _body(1, 40), "configure": _body(5, 50), "draft": _body(10, 100)}


def op1_tool_calls(spark, sf_dir: str) -> DataFrame:
    turns = picked(table(spark, sf_dir, "conversations"), conv_id="conv_id", turn="turn", role="role", text="text")
    return link(*turns_as_calls(turns), SCHEMAS)
