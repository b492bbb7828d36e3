from __future__ import annotations

import json
import random
import re
from collections import Counter

from pyspark.sql import functions as F

from evograph.llm import chat_format as C
from evograph.llm import quality_rules as R

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def measures(t):
    w = WORD.findall(t or "")
    grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    n = Counter(grams)
    rep = {p for i, g in enumerate(grams) if n[g] > 1 for p in (i, i + 1, i + 2)}
    lines, seen, dup = (t or "").split("\n"), set(), 0
    for x in lines:
        if WORD.search(x):
            dup += x in seen
            seen.add(x)
    failed = len(w) < 50 or 100 * len(rep) > 50 * len(w)
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""), dup, len(rep), failed


def test_measures(docs_of, empty):
    r = random.Random(0)
    ts = [None, "", " \n\t", "a", "a b c a b c", "x#$ é|é\nx#$ é|é\n\n \n", "ab " * 60]
    ts += [r.choice([" ", "\n", "  "]).join(r.choice("a b c d e f g #x &y ü".split()) for _ in range(r.randrange(120))) for _ in range(60)]
    got = {x["doc_id"]: x for x in R.rules(docs_of(ts)).collect()}
    for k, t in enumerate(ts):
        x = got[k]
        assert (x["n_words"], x["word_chars"], x["n_symbols"], x["n_dup_lines"], x["n_repeat_words"], x["base_failed"]) == measures(t)
    assert R.rules(empty).count() == 0 and R.filter_documents(empty).count() == 0


def test_boilerplate(spark):
    r = random.Random(1)
    body = lambda: "\n".join(" ".join("".join(r.choice("abcdefghij") for _ in range(7)) for _ in range(12)) for _ in range(6))
    rows = [(k, f"Subscribe  NOW {k}\n" + body(), "en", "h1" if k % 3 else None, 1) for k in range(150)]
    rows += [(500, "subscribe now 7\n" + body(), "en", "h2", 1), (501, "\n".join(f"Subscribe now {k}" for k in range(40)) + "\n" + "only ten words stay here so it is depleted now", "en", "h1", 1)]
    rows += [(600 + k, rows[1][1], "en", "h3", 1) for k in range(80)]  # copies of one text are no boilerplate
    rows += [(700 + k, f"Page {k % 12} of the guide\nFollow us on the network\n" + rows[k % 12][1].split("\n", 1)[1], "en", "h4", 1) for k in range(30)]  # documents count, not texts
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumn("v_key", F.lit(0))
    kept = {x["doc_id"]: x for x in R.filter_documents(df, min_docs=20, max_share=0.3).collect()}
    assert kept[1]["text"] == rows[1][1].split("\n", 1)[1] and kept[1]["n_chars"] == len(kept[1]["text"])
    assert kept[500]["text"] == rows[150][1] and all(600 + k in kept for k in range(80))
    assert all("Follow" not in kept[700 + k]["text"] and "Page" not in kept[700 + k]["text"] for k in range(30))
    verdict = {x["doc_id"]: x for x in R.rules(df, min_docs=20, max_share=0.3).collect()}
    assert set(kept) == {k for k, x in verdict.items() if x["kept"]}
    again = R.rules(df.unionByName(df), 20, 0.3).where("doc_id = 1").collect()
    assert len(again) >= 1 and len({x["n_boilerplate_words"] for x in again}) == 1


def test_limits_work_on_small_and_large_hosts(spark):
    """With the registered limits, a line in more than a tenth of a host goes, on any host of more than ten documents."""
    r = random.Random(2)
    body = lambda: " ".join("".join(r.choice("abcdefghij") for _ in range(7)) for _ in range(60))
    rows = [(k, ("All rights reserved here\n" if k < 11 else "") + ("Seldom seen line\n" if 20 <= k < 30 else "") + body(), "small") for k in range(40)]
    rows += [(1000 + k, ("Menu of the page\n" if k < 90 else "") + ("Found in few pages\n" if 100 <= k < 170 else "") + body(), "large") for k in range(800)]
    lost = {x["doc_id"]: x["n_boilerplate_words"] for x in R.rules(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert {k for k, n in lost.items() if n} == {*range(11), *range(1000, 1090)}


def test_rules_are_native(docs_of):
    plan = R.rules(docs_of(["a b"]))._jdf.queryExecution().executedPlan().toString() + C.chat_digest(C.with_probe(docs_of(["a"]).selectExpr("doc_id AS conv_id", "0L AS turn", "'user' AS role", "text")))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


def test_chat_round_trip(spark):
    texts = ["", None, "\\### Assistant: </turn> ok", "<turn:user>\nhi</turn>\n", "\\b\\l\\g\\\\<>", "a\n\nb", "é😀", "x" * 5000]
    rows = [(1, k, r, t) for k, (r, t) in enumerate((r, t) for t in texts for r in ("user", "assistant"))] + [(2, 0, None, "a"), (2, 0, "assistant", "b"), (2, 0, "assistant", "b"), (None, 0, "we>ird<r", "c")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("extra", F.lit(1))
    f = C.format_turns(C.row_turns(df))
    got = {x["conv_id"]: x for x in f.withColumns({"turns": C.read_turns(F.col("formatted")), "loss": C.read_loss(F.col("formatted"), F.col("loss_mask"))}).collect()}
    assert [(t["role"], t["text"]) for t in got[1]["turns"]] == [(r, t or "") for t in texts for r in ("user", "assistant")]
    assert got[1]["loss"] == "".join(t or "" for t in texts)
    assert [(t["role"], t["text"]) for t in got[2]["turns"]] == [("", "a"), ("assistant", "b"), ("assistant", "b")]
    assert got[None]["turns"][0]["role"] == "we>ird<r"
    assert C.chat_digest(df.where("conv_id = 5")).count() == 0


def test_layouts(spark):
    recs = [
        {"messages": [{"role": "user", "content": "hi"}, {"role": "assistant", "content": "yo"}]},
        {"conversations": [{"from": "human", "value": "q"}, {"from": "gpt", "value": "a"}]},
        {"instruction": "do", "input": "", "output": "done"},
        {"instruction": "do", "output": "done"},
        {"prompt": "p", "completion": "c"},
        {"prompt": "p", "response": "c"},
        {"question": "p", "answer": "c"},
        {"nothing": 1},
    ]
    df = spark.createDataFrame([(k, json.dumps(x)) for k, x in enumerate(recs)] + [(90, None), (91, "{bad")], "id long, rec string")
    got = {}
    for r in C.json_turns(df, "id", "rec").orderBy("conv_id", "turn").collect():
        got.setdefault(r["conv_id"], []).append((r["role"], r["text"]))
    assert got[0] == [("user", "hi"), ("assistant", "yo")] and got[1] == [("user", "q"), ("assistant", "a")]
    assert got[2] == [("system", "do"), ("assistant", "done")] and got[3] == [("user", "do"), ("assistant", "done")]
    assert got[4] == got[5] == got[6] == [("user", "p"), ("assistant", "c")] and 7 not in got and 90 not in got
    assert C.unknown_layouts(df.where("id = 7"), "rec").count() == 1
    other = spark.createDataFrame([(1, 0, "user", "x")], "conversation long, position long, speaker string, utterance string")
    assert C.row_turns(other).columns == ["conv_id", "turn", "role", "text"]
