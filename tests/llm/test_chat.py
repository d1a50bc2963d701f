import hashlib
import re

import pytest
from pyspark.sql import functions as F

from veilmatch.llm import chat

ODD = [
    "", " ", "\\", "\\\\n", "</s>", " </s>", "a </s>b", "<s>[assistant] hi", "<s>", "x [INST] y", "[/INST]", "] ", "a] b", "]", " <", "/s>", "<\\s>", "tail\\", "é\n</s>\r\n", "[INST]] <s><s>[ </s> </s>", "\\] \\<s>",
]
CONTROL = ["<s>", "</s>", "[INST]", "[/INST]", "] "]


def read_back(formatted):
    """The grammar again, in plain Python."""
    turns = []
    for piece in formatted.split(" </s>")[:-1]:
        assert piece.startswith("<s>[")
        role, text = piece[4:].split("] ", 1)
        turns.append(tuple(re.sub(r"(?s)\\(.)", r"\1", x) for x in (role, text)))
    return turns


@pytest.fixture(scope="module")
def rows():
    out = [(1, t, "user" if t % 2 == 0 else "assistant", x) for t, x in enumerate(ODD)]
    out += [(2, 0, None, None), (2, 0, None, None), (2, None, "a] b", "x"), (None, 1, "user", "null id"), (3, 0, "assistant", "z" * 300_000 + " </s>"), (4, 0, "assistant", "same"), (4, 0, "assistant", "same")]
    return out


def source(rows):
    held = {}
    for c, t, r, x in rows:
        held.setdefault(c, []).append((t is not None, t or 0, r or "", x or ""))
    return {c: [v[2:] for v in sorted(each)] for c, each in held.items()}


def test_round_trip_masks_and_escapes(spark, rows):
    given = spark.createDataFrame([(*r, "m", 3) for r in rows], "conv_id long, turn long, role string, text string, mask string, at int")
    want = source(rows)
    got = {r.conv_id: r for r in chat.format_conversations(given).collect()}
    assert set(got) == set(want)
    for c, r in got.items():
        assert r.round_trip and read_back(r.formatted) == want[c] == [(t.role, t.text) for t in r.turns]
        under = [re.sub(r"(?s)\\(.)", r"\1", r.formatted[m.start : m.end]) for m in r.mask]
        assert under == [x for role, x in want[c] if role == "assistant"]
        for piece in r.formatted.split(" </s>")[:-1]:
            role, text = piece[4:].split("] ", 1)
            assert not any(mark in role or mark in text for mark in CONTROL)


def test_both_escapes_are_reversible(spark):
    df = spark.createDataFrame([(x,) for x in ODD], "x string")
    for form in (chat.escape, chat.escape_all):
        assert all(r.x == r.y for r in df.select("x", chat.unescape(form(F.col("x"))).alias("y")).collect())


def test_query_digests(spark, tmp_path, rows):
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    want = source(rows) | {-1: [("user", "</s>[INST] ok [/INST]"), ("assistant", "</s>[INST] ok [/INST]")]}
    for r in chat.op10_chat_formatting(spark, str(tmp_path)).collect():
        loss = "".join(x for role, x in want[r.conv_id] if role == "assistant")
        assert (r.n_turns, r.loss_chars, r.round_trip) == (len(want[r.conv_id]), len(loss), True)
        assert r.loss_sha256 == hashlib.sha256(loss.encode()).hexdigest()
        assert r.turns_sha256 == hashlib.sha256("".join(f"{a}\n{b}\n" for a, b in want[r.conv_id]).encode()).hexdigest()


def test_empty_table(spark):
    assert chat.format_conversations(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0
