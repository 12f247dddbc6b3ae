import collections
import json
import random

import regex

from hetpart.llm import tool_calls as T

SCHEMAS = {"t": {"type": "object", "properties": {"x": {"type": "number"}}, "required": ["x"]}}
CALLS = "conv_id long, call_id string, pos long, tool string, arguments string, after array<string>"
RESULTS = "conv_id long, call_id string, pos long, content string"


def test_linking_order_and_validation(spark):
    calls = spark.createDataFrame(
        [(1, "a", 5, "t", '{"x":1.0,"b":[2,1]}', ["b"]), (1, "b", 7, "t", '{"x":"q"}', ["c"]), (1, "c", 6, "t", '{"x":3,"x":4}', None), (1, "d", 9, "u", "", ["zz"]), (1, "d", 10, "t", '{"x":2}', []), (1, "e", 20, "t", '{"x":2}', ["f"]), (1, "f", 21, "t", '{"x":2}', ["e"]), (1, "g", 22, "t", '"\\ud800"', ["f"]), (None, "a", 1, "t", '{"x":1}', []), (2, None, 1, "t", "[" * 100000, [])],
        CALLS,
    )
    results = spark.createDataFrame([(1, "a", 6, "ok"), (1, "a", 8, "later"), (1, "b", 2, "early"), (1, "q", 3, "orphan"), (None, "a", 2, "n")], RESULTS)
    rows = T.link(calls, results, SCHEMAS).orderBy("conv_id", "seq_major", "seq_level", "pos", "call_id").collect()
    one = [r for r in rows if r["conv_id"] == 1]
    assert [(r["call_id"], r["status"]) for r in one] == [("q", "orphan"), ("c", "open"), ("b", "early"), ("a", "linked"), ("d", "open"), ("d", "repeated"), ("e", "open"), ("f", "open"), ("g", "open")]
    by = {(r["call_id"], r["status"]): r for r in one}
    assert by["a", "linked"]["n_results"] == 2 and json.loads(by["a", "linked"]["record"])["result"] == "ok"
    assert '"arguments":{"b":[2,1],"x":1}' in by["a", "linked"]["record"]
    assert by["b", "early"]["errors"] == ["$.x: not number"] and by["e", "open"]["on_cycle"] and not by["g", "open"]["on_cycle"]
    assert "missing dependency zz" in by["d", "open"]["errors"] and by["c", "open"]["errors"] == ["arguments: a name stands twice"]
    assert len([r for r in rows if r["status"] == "unnamed"]) == 2


def test_long_tangle_is_peeled(spark):
    n = 12  # each call depends on the one that stands after it
    calls = spark.createDataFrame([(1, f"c{k:02}", k, "t", '{"x":1}', [f"c{k + 1:02}"] if k < n - 1 else []) for k in range(n)], CALLS)
    rows = T.link(calls, spark.createDataFrame([], RESULTS), SCHEMAS).orderBy("seq_major", "seq_level", "pos").collect()
    assert [r["call_id"] for r in rows] == [f"c{k:02}" for k in reversed(range(n))] and not any(r["on_cycle"] for r in rows)


def brute_calls(turns):
    """Calls and results by conversation, read from (conv_id, turn, role, text) row by row."""
    words = {i: regex.findall(r"[\p{L}\p{N}]+", (t or "").lower()) for i, (_, _, _, t) in enumerate(turns)}
    ident = {}
    for i, (c, n, role, _) in enumerate(turns):
        if role in ("user", "system"):
            x = " ".join(words[i][:2])
            ident[c, n] = min(x, ident.get((c, n), x))
    calls, results = collections.defaultdict(list), collections.defaultdict(list)
    for i, (c, n, role, text) in enumerate(turns):
        w = words[i]
        if role in ("user", "system"):
            ways = ([1, 2] if len(w) % 2 == 0 else []) + ([-1, -2] if len(w) % 3 == 0 else [])
            after = sorted({ident[c, n + k] for k in ways if (c, n + k) in ident})
            tool = "configure" if role == "system" else "draft" if "\n" in (text or "") else "reply"
            calls[c].append((n, {"prompt": text, "turn": n, "n_words": len(w), "opening": w[0] if w else None}, tool, " ".join(w[:2]), after))
        elif role == "assistant":
            results[c].append((n, ident.get((c, n - 1)), text))
    return calls, results


def brute(turns):
    """conv_id -> multiset of rows, by plain sorting, merging and Kahn's algorithm."""
    calls, results = brute_calls(turns)
    limits = {"reply": (1, 40), "configure": (5, 50), "draft": (10, 100)}
    out = []
    for c in set(calls) | set(results):
        first, rest = {}, []
        for pos, body, tool, i, after in sorted(calls[c], key=lambda x: (x[0], json.dumps(x[1], ensure_ascii=False), x[2])):
            if i in first:
                rest.append((pos, i))
            else:
                first[i] = (pos, body, tool, after)
        key = {i: (x[0], i) for i, x in first.items()}
        back = sorted((key[i], key[d]) for i, x in first.items() for d in x[3] if d in first and key[d] >= key[i])
        tangles = []
        for lo, hi in back:
            if tangles and lo <= tangles[-1][1]:
                tangles[-1][1] = max(tangles[-1][1], hi)
            else:
                tangles.append([lo, hi])
        place = {}
        for lo, hi in tangles:
            left, level = {i for i in first if lo <= key[i] <= hi}, 0
            while left:
                ready = {i for i in left if not any(d in left for d in first[i][3])}
                for i in ready or left:
                    place[i] = (lo[0], level, not ready)
                left, level = (left - ready, level + 1) if ready else (set(), level)
        for i, (pos, body, tool, after) in first.items():
            mine = sorted((p, x) for p, j, x in results[c] if j == i and p > pos)
            any_ = any(j == i for _, j, _ in results[c])
            low, high = limits[tool]
            bad = ["$.n_words: minimum"] * (body["n_words"] < low) + ["$.n_words: maximum"] * (body["n_words"] > high)
            bad += ["$.opening: not string"] if body["opening"] is None else ["$.opening: maxLength"] * (len(body["opening"]) > 9)
            bad += ["$.prompt: not string"] if body["prompt"] is None else ["$.prompt: minLength"] * (body["prompt"] == "")
            major, level, cyclic = place.get(i, (pos, 0, False))
            out.append((c, i, pos, tool, "linked" if mine else "early" if any_ else "open", major, level, cyclic, len(mine), mine[0][0] if mine else None, tuple(bad + ["on a cycle"] * cyclic)))
        out += [(c, i, pos, "repeated") for pos, i in rest] + [(c, i, pos, "orphan") for pos, i, _ in results[c] if i not in first]
    return collections.Counter(out)


def rows_of(df):
    def plain(r):
        if r["status"] in ("repeated", "orphan"):
            return (r["conv_id"], r["call_id"], r["pos"], r["status"])
        return (*(r[k] for k in ("conv_id", "call_id", "pos", "tool", "status", "seq_major", "seq_level", "on_cycle", "n_results", "result_pos")), tuple(r["errors"]))

    return collections.Counter(map(plain, df.collect()))


def test_query_equals_brute_force(spark):
    turns = [tuple(r) for r in spark.read.parquet("/root/testdata/sf0.01/conversations.parquet").select("conv_id", "turn", "role", "text").collect()]
    rng = random.Random(5)
    for c, n in ((10**6, 160), (10**6 + 1, 60)):  # long conversations of few words: tangles, cycles, repeated ids
        turns += [(c, t, rng.choice(["user", "user", "system", "assistant"]), rng.choice([None, "", "\n", *(" ".join(rng.choices("ab cd ef gh Unbelievable".split(), k=rng.randrange(1, 60))) for _ in range(7))])) for t in range(n)]
    turns += turns[-30:]  # repeated rows
    want = brute(turns)
    got = rows_of(T.link(*T.turns_as_calls(spark.createDataFrame(turns, "conv_id long, turn long, role string, text string").repartition(5)), T.SCHEMAS))
    assert got == want, [x for k in range(4) for x in sorted(map(str, (got - want) if k % 2 == 0 else (want - got)))[k:k + 1]]
    kinds = collections.Counter(x[4] if len(x) > 4 else x[3] for x in want)
    assert all(kinds[k] for k in ("linked", "open", "repeated", "orphan")) and any(len(x) > 4 and x[7] for x in want) and any(len(x) > 4 and x[6] > 2 and not x[7] for x in want)


def test_order_respects_dependencies_and_records_are_canonical(spark, sf):
    rows = T.link(*T.turns_as_calls(spark.read.parquet("/root/testdata/sf0.01/conversations.parquet")), T.SCHEMAS).collect()
    seen, moved = set(), 0
    for r in sorted((r for r in rows if r["status"] not in ("repeated", "orphan")), key=lambda r: (r["conv_id"], r["seq_major"], r["seq_level"], r["pos"], r["call_id"])):
        record = json.loads(r["record"])
        assert r["record"] == T.canonical(record)
        assert r["on_cycle"] or all((r["conv_id"], a) in seen for a in record["after"]), r
        moved += r["seq_level"] > 0
        seen.add((r["conv_id"], r["call_id"]))
    assert moved > 5


def test_tags_and_empty_tables(spark):
    turns = spark.createDataFrame([(1, 0, "assistant", 'so <tool_call>{"id":"k","name":"t","arguments":{"x":2}}</tool_call>'), (1, 1, "tool", '<tool_result id="k">4</tool_result>'), (2, 0, "user", None), (2, 1, "user", "")], "conv_id long, turn long, role string, text string")
    r = T.link(*T.tagged(turns), SCHEMAS).collect()
    assert len(r) == 1 and r[0]["status"] == "linked" and r[0]["errors"] == []
    empty = turns.where("false")
    assert T.link(*T.tagged(empty), SCHEMAS).count() == 0 and T.link(*T.turns_as_calls(empty), T.SCHEMAS).count() == 0
    assert T.link(*T.turns_as_calls(turns), T.SCHEMAS).count() == 2 + 1


def test_schemas_and_numbers():
    s = {"type": "object", "properties": {"n": {"type": "integer", "minimum": 1}, "s": {"enum": ["a"]}, "l": {"type": "array", "items": {"type": "string"}, "maxItems": 1}}, "additionalProperties": False}
    assert T.violations({"n": 0, "s": "b", "l": [1, "x"], "z": 1}, s) == ["$.l: maxItems", "$.l[0]: not string", "$.n: minimum", "$.s: not in enum", "$.z: not allowed"]
    assert T.violations({"n": 2.0, "s": "a"}, s) == []
    assert T.canonical({"b": 1.50, "a": [1.0, -0.0, True, None, "é"]}) == '{"a":[1,0,true,null,"é"],"b":1.5}'
