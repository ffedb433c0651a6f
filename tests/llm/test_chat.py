"""Chat formatting: layouts, round trips, digests against plain code."""

import hashlib
import json
from collections import defaultdict

from hypothesis import given, settings
from hypothesis import strategies as st

from gridmask.llm import chat, queries

NASTY = st.lists(st.sampled_from([*chat.FOREIGN, chat.OPEN, chat.MIDDLE, chat.CLOSE, "\\", "\n", "<", "|", "a", "é", "\\<", "assistant"]), max_size=12).map("".join)


@settings(max_examples=300, deadline=None)
@given(st.lists(st.tuples(NASTY, NASTY), max_size=5))
def test_round_trip(turns):
    text, found = "", []
    for role, body in turns:
        piece, s, e = chat.format_turn(role, body)
        found.append(chat.unescape(piece[s:e]))
        text += piece
    assert chat.parse(text) == turns and found == [b for _, b in turns]
    for mark in chat.FOREIGN[:-1]:
        assert all(text[i - 1] == "\\" for i in range(len(text)) if text.startswith(mark, i))


LAYOUTS = [
    ({"messages": [{"role": "system", "content": "s"}, {"role": "user", "content": "u"}, {"role": "assistant", "content": "a"}]}, [("system", "s"), ("user", "u"), ("assistant", "a")], "messages"),
    ({"id": 3, "conversations": [{"from": "human", "value": "u"}, {"from": "gpt", "value": "a"}]}, [("user", "u"), ("assistant", "a")], "conversations"),
    ({"instruction": "i", "input": "x", "output": "o"}, [("user", "i\n\nx"), ("assistant", "o")], "instruction"),
    ({"instruction": "i", "input": "", "output": "o", "system": "s"}, [("system", "s"), ("user", "i"), ("assistant", "o")], "instruction"),
    ({"prompt": "p", "completion": "c", "meta": {"k": [1, 2]}}, [("user", "p"), ("assistant", "c")], "prompt_completion"),
    ({"question": "q", "context": "c", "answer": "a"}, [("user", "c\n\nq"), ("assistant", "a")], "question_answer"),
    ({"messages": [{"role": "user", "content": [{"type": "text", "text": "x"}, {"type": "text", "text": "y"}]}]}, [("user", "xy")], "messages"),
    ({"foo": 1}, None, None),
]


def test_layouts(spark):
    registry = chat.Registry()
    for record, turns, name in LAYOUTS:
        assert registry.turns(record) == turns and (registry.mapping(record).name if turns else None) == name
    n = len(registry.known)
    assert registry.turns({"prompt": "other", "completion": "words", "meta": {"k": [5]}}) == [("user", "other"), ("assistant", "words")] and len(registry.known) == n
    rows = [(json.dumps(r), "clash") for r, _, _ in LAYOUTS] + [(None, ""), ("no json", ""), ("[1]", "")]
    got = chat.format_records(spark.createDataFrame(rows, "record string, layout string")).collect()
    for r, (_, turns, name) in zip(got, LAYOUTS):
        assert r.layout == name
        if turns:
            assert chat.parse(r.formatted) == turns and r.n_turns == len(turns)
            assert [chat.unescape(r.formatted[s.start : s.end]) for s in r.loss_spans] == [t for role, t in turns if role == "assistant"]
    assert [r.formatted for r in got[len(LAYOUTS) - 1 :]] == [None] * 4
    assert chat.format_records(spark.createDataFrame([], "record string")).count() == 0


def test_row_layouts(spark):
    want = {1: [("user", "u <s>"), ("assistant", "a")], 2: [("user", ""), ("assistant", "b")]}
    tables = [
        spark.createDataFrame([(1, 0, "user", "u <s>", "x"), (1, 1, "assistant", "a", "x"), (2, 0, "user", None, "x"), (2, 1, "assistant", "b", "x")], "conv_id long, turn int, role string, text string, note string"),
        spark.createDataFrame([(1, 0, "human", "u <s>"), (1, 1, "gpt", "a"), (2, 0, "human", ""), (2, 1, "gpt", "b")], "conv_id long, turn int, from string, value string"),
        spark.createDataFrame([(1, 0, "u <s>", "a"), (2, 0, None, "b")], "conv_id long, turn int, prompt string, response string"),
        spark.createDataFrame([(1, 0, [("user", "u <s>"), ("assistant", "a")]), (2, 0, [("user", None), ("assistant", "b")])], "conv_id long, turn int, messages array<struct<role:string, content:string>>"),
    ]
    for df in tables:
        got = {r.conv_id: chat.parse(r.formatted) for r in chat.format_conversations(df).collect()}
        assert got == want
    try:
        chat.format_conversations(spark.createDataFrame([(1, 0, 3)], "conv_id long, turn int, n int"))
        raise AssertionError("a table without a layout must be refused")
    except ValueError:
        pass


def plain_digests(rows):
    by = defaultdict(list)
    for r in rows:
        by[r[0]].append(r)
    out = {}
    for c, turns in by.items():
        turns.sort(key=lambda r: (r[1] is not None, r[1] or 0, r[2] is not None, r[2] or "", r[3] is not None, r[3] or ""))
        loss = "".join(t or "" for _, _, role, t in turns if role == "assistant")
        out[c] = (len(turns), hashlib.sha256("".join(f"{role or ''}\n{t or ''}\n" for _, _, role, t in turns).encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest())
    return out


def test_conversations(spark, sf_dir):
    rows = [tuple(r) for r in spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text").collect()]
    got = {r.conv_id: (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256) for r in queries.op3_chat_format(spark, sf_dir).collect()}
    probe = "</s>[INST] ok [/INST]"
    assert got == plain_digests([*rows, (-1, 0, "user", probe), (-1, 1, "assistant", probe)])


def test_odd_conversations(spark):
    rows = [(1, 2, "assistant", "b"), (1, 1, "user", None), (1, 1, "user", "a"), (1, None, None, "x"), (2, 1, "assistant", ""), (None, 1, "assistant", "n"), (3, 1, "assistant", "é" * 30000), (3, 1, "assistant", "é" * 30000), *((4, i, "assistant" if i % 2 else "human", f"<|text|>{i}\\") for i in range(3000))]
    df = spark.createDataFrame([(*r, 1) for r in rows], "conv_id long, turn long, role string, text string, part int")
    for size in (1 << 20, 100):
        got = {r.conv_id: (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256) for r in chat.read_digests(chat.format_conversations(df, size)).collect()}
        assert got == plain_digests(rows)
    assert chat.read_digests(chat.format_conversations(df.limit(0))).count() == 0
