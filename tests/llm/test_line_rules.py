import collections
import re

from hetpart.llm import line_rules as L


def brute(t):
    t = t or ""
    w = [x for x in re.split("[\x20\x09-\x0d]+", t) if x]
    c = collections.Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    cover = {i + k for i in range(len(w) - 2) if c[tuple(w[i : i + 3])] > 1 for k in range(3)}
    seen, dup = set(), 0
    for line in t.split("\n"):
        if re.search("[^\x20\x09-\x0d]", line):
            dup += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in t), dup, len(cover), len(w) < 50 or 100 * len(cover) > 50 * len(w)


def test_base_counts_equal_brute_force(frame, sample, awkward):
    docs = [*sample.items(), *awkward, (5, " a b\x0bc a b c\n\n x y 😀 "), (6, "x x x x"), (7, "\n".join(f"q w e r t z u i o p {i % 7}" for i in range(300))), (8, "a b c")]
    docs = [(i, t) for i, t in docs if i not in (5, 6, 7, 8)] + docs[-4:]
    got = L.judge(frame(docs)).collect()
    want = dict((i, brute(t)) for i, t in docs)
    assert len(got) == len(docs)
    for r in got:
        assert tuple(r)[1:7] == want[r["doc_id"]]


def prose(k, n=60):
    return " ".join(f"word{k}x{i}" for i in range(n))


def test_boilerplate_counts_documents_of_a_host(spark):
    solo = prose(1).replace("word", "term")
    foot = "\n".join(" ".join(f"All{i}x{j}  RIGHTS{j}y" for j in range(5)) + " page" for i in range(12))
    rows = [(k, f"{prose(k)}\n{foot}", "h1") for k in range(25)]
    rows += [(100 + k, f"{prose(k)}\n{foot}", "h2") for k in range(5)]
    rows += [(200 + k, prose(999), "h1") for k in range(40)]  # copies are documents of their own
    rows += [(300, solo, "h1")] * 30  # rows of one document
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    for bound in (100_000, 0):
        r = {x["doc_id"]: x for x in L.judge(docs, broadcast_rows=bound).collect()}
        assert r[0]["boilerplate_chars"] > 0 and not r[0]["kept"] and not r[0]["base_failed"]
        assert r[100]["boilerplate_chars"] == 0 and r[100]["kept"]
        assert r[200]["boilerplate_chars"] > 0 and not r[200]["kept"] and r[300]["kept"] and r[300]["boilerplate_chars"] == 0
    out = {x["doc_id"]: x["text"] for x in L.cleaned(docs, min_kept=0.1).collect()}
    assert out[0] == prose(0) and out[100].endswith("page") and 200 not in out and out[300] == solo


def test_plan_is_native_and_empty(spark, frame):
    df = L.judge(frame([(1, prose(1))]))
    assert "Python" not in df._jdf.queryExecution().toString() and df.first()["kept"]
    assert L.judge(frame([])).count() == 0 and L.cleaned(frame([])).count() == 0
