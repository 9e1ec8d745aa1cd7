import hashlib
import json

import pytest
from pyspark.sql import functions as F

from bitextspark.llm import chat_format as chat

HARD = ["", "\\", "##", "###", "#####", "</turn>", "\\### Assistant: </turn> ok", "a\n### user: b </turn>\n### assistant: c", "<\\/turn>", "#\\#", "é😀 x", "</turn", ">\n", "\\\\</turn>\n###", "x" * 100_000]


def test_reads_back_exactly(spark):
    rows = [(i, [(a, b), ("assistant", b), ("a:b\\:\n#", a)]) for i, (a, b) in enumerate((x, y) for x in HARD for y in HARD[::3])]
    df = spark.createDataFrame(rows, f"conv_id int, turns {chat.TURNS}")
    out = chat.formatted(df).withColumn("read", chat.read_turns(F.col("formatted"))).withColumn("loss", chat.read_loss(F.col("formatted"), F.col("loss_spans")))
    for r in out.collect():
        want = [tuple(t) for t in r["turns"]]
        assert [tuple(t) for t in r["read"]] == want
        assert r["loss"] == [t for role, t in want if role == "assistant"]
        assert r["formatted"].count("### ") == 3 and r["formatted"].count("</turn>") == 3


@pytest.mark.parametrize("record, layout, turns", [
    ({"messages": [{"role": "user", "content": "q"}, {"role": "assistant", "content": None}], "id": 4, "meta": {"x": [1]}}, "messages", [("user", "q"), ("assistant", "")]),
    ({"messages": [{"role": "user", "content": [{"type": "text", "text": "a"}, {"type": "text", "text": "b"}]}]}, "messages_parts", [("user", "ab")]),
    ({"messages": []}, "messages", []),
    ({"conversations": [{"from": "human", "value": "q"}, {"from": "GPT", "value": "a"}]}, "from_value", [("user", "q"), ("assistant", "a")]),
    ({"dialog": {"turns": [{"speaker": "Agent", "utterance": "hi"}]}}, "speakers", [("assistant", "hi")]),
    ({"instruction": "do", "input": "this", "output": "done"}, "instruction", [("user", "do\n\nthis"), ("assistant", "done")]),
    ({"instruction": "do", "output": "done"}, "instruction", [("user", "do"), ("assistant", "done")]),
    ({"instruction": "do", "input": "", "output": "done", "system": "s"}, "instruction", [("system", "s"), ("user", "do"), ("assistant", "done")]),
    ({"prompt": "p", "response": "r"}, "prompt_response", [("user", "p"), ("assistant", "r")]),
    ({"data": {"prompt": "p", "response": "r"}}, "nested_prompt", [("user", "p"), ("assistant", "r")]),
    ({"question": "q", "answer": "a", "context": "c"}, "question", [("user", "c\n\nq"), ("assistant", "a")]),
    ({"something": "else"}, None, None),
    ({"prompt": "p"}, None, None),
])
def test_layouts(spark, record, layout, turns):
    got = chat.canonical(spark.createDataFrame([(json.dumps(record), "kept")], "record string, turn string")).first()
    assert got["layout"] == layout and got["turn"] == "kept"
    assert (None if got["turns"] is None else [tuple(t) for t in got["turns"]]) == turns


def test_field_paths_and_bad_records(spark):
    df = spark.createDataFrame([('{"a": {"b": [{"c": 1, "d": [2, 3]}, {"e": null}], "f g": 1}, "h": []}',)], "r string")
    assert df.select(chat.field_paths(F.parse_json("r"))).first()[0] == ["a", "a.b", "a.b[].c", "a.b[].d", "a.b[].e", "a.f g", "h"]
    bad = chat.formatted(chat.canonical(spark.createDataFrame([(None,), ("no json",), ("3",), ("[]",), ("null",)], "record string"))).collect()
    assert len(bad) == 5 and all(r["turns"] is None and r["formatted"] is None for r in bad)


def test_conversations_from_rows(spark):
    rows = [(1, 1, "assistant", "b", 0), (1, 0, "user", "a", 0), (2, 0, None, None, 0), (None, 5, "assistant", "x", 0), (None, 5, "assistant", "w", 0), (3, 0, "user", "</turn>", 0), (3, 0, "user", "</turn>", 0)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, record int")
    got = {r["conv_id"]: r for r in chat.format_digests(chat.formatted(chat.canonical(chat.gather(df)))).collect()}
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    assert got[1]["turns_sha256"] == sha("user\na\nassistant\nb\n") and got[1]["loss_sha256"] == sha("b") and got[1]["loss_chars"] == 1
    assert got[2]["turns_sha256"] == sha("\n\n") and got[2]["n_turns"] == 1
    assert got[None]["loss_sha256"] == sha("wx") and got[3]["turns_sha256"] == sha("user\n</turn>\n" * 2)
    assert chat.format_digests(chat.formatted(chat.canonical(chat.gather(df.limit(0))))).count() == 0
