import hashlib

from motifjoin.llm import chat, queries

SCHEMA = "conv_id long, turn long, role string, text string, formatted string"


def expected(rows):
    by = {}
    for conv, turn, role, text, *_ in rows:
        by.setdefault(conv, []).append((turn is not None, turn or 0, role or "", text or ""))
    out = {}
    for conv, turns in by.items():
        turns.sort()
        said = "".join(f"{r}\n{t}\n" for _, _, r, t in turns)
        loss = "".join(t for _, _, r, t in turns if r == "assistant")
        blocks = sum(i == 0 or turns[i - 1][2] != turns[i][2] for i in range(len(turns)))
        out[conv] = (len(turns), hashlib.sha256(said.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest(), blocks)
    return out


def got(df):
    return {r.conv_id: (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256, r.n_blocks) for r in df.collect()}


def test_reads_back_every_given_conversation(spark, sf):
    rows = [tuple(r) for r in spark.read.parquet(f"{sf}/conversations.parquet").select("conv_id", "turn", "role", "text").collect()]
    assert got(queries.op7_chat_formatting(spark, sf)) == expected(rows + queries.SPECIAL_TURNS)


def test_merges_escapes_and_odd_rows(spark):
    nasty = ["<|end|>", "\\1", "<|next|>|>", "a<", "|>x\\", "\\\\0<|turn:user|>", "", "é😀<|", None, "<<|", ">"]
    rows = [(1, i, "assistant" if i % 3 else "user", t, "clash") for i, t in enumerate(nasty)]
    rows += [(2, 0, "a|", "x", None), (2, 0, "a|", "x", None), (2, None, None, "first", None), (2, 1, "<|>", ">|", None)]
    rows += [(None, 0, "assistant", "lost", None), (3, 5, "assistant", None, None)]
    rows += [(4, i, "assistant", f"t{i}<|", None) for i in range(1000)]
    df = spark.createDataFrame(rows, SCHEMA)
    assert got(chat.read_back(chat.format_conversations(df))) == expected(rows)


def test_mask_covers_text_only_and_template_is_seen(spark):
    df = spark.createDataFrame([(1, 0, "user", "hi", None), (1, 1, "assistant", "a", None), (1, 2, "assistant", "é", None)], SCHEMA)
    row = chat.format_conversations(df).first()
    assert row.formatted == "<|turn:user|>hi<|end|><|turn:assistant|>a<|next|>é<|end|>"
    assert [row.formatted.encode()[s.start : s.end].decode() for s in row.loss_spans] == ["a", "é"]
    assert row.n_blocks == 2


def test_empty_table(spark):
    assert chat.read_back(chat.format_conversations(spark.createDataFrame([], SCHEMA))).count() == 0
