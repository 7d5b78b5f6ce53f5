"""Chat formatting with Spark expressions only.

A conversation is collected as an array of turn structs and sorted; adjacent
turns of one role merge into a block; blocks are concatenated. The template:

    <|turn:ROLE|>TEXT<|next|>TEXT<|end|>

``<|next|>`` keeps the border between two merged turns, so the rows can be read
back. Inside roles and texts the control strings are escaped, reversibly:
``\\`` becomes ``\\0``, ``<|`` becomes ``\\1`` and ``|>`` becomes ``\\2``. After
escaping, every backslash is followed by a digit, so undoing the three
replacements in reverse order is exact.

The loss mask is a list of byte ranges of the formatted text's UTF-8 form
(``loss_spans``), one per assistant turn, that cover its escaped text and no
control string.

Defined results: null text or null role is the empty string; null turn sorts
first; ties in ``turn`` sort by role, then text; repeated rows are repeated
turns; rows with null ``conv_id`` form one conversation. A conversation is one
output row and has to fit in one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed values of the template.
OPEN, NAMED, NEXT, END = "<|turn:", "|>", "<|next|>", "<|end|>"
ESCAPES = (("\\", "\\0"), ("<|", "\\1"), ("|>", "\\2"))
#: Turns whose offsets are summed together; keeps the running sums linear.
STRIDE = 128


def escape(text: Column) -> Column:
    for plain, code in ESCAPES:
        text = F.replace(text, F.lit(plain), F.lit(code))
    return text


def unescape(text: Column) -> Column:
    for plain, code in reversed(ESCAPES):
        text = F.replace(text, F.lit(code), F.lit(plain))
    return text


def _starts(lengths: Column) -> Column:
    """Exclusive running sums of an array, by strides: array<array<long>> per stride."""
    zero = F.lit(0).cast("long")
    strides = F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil(F.size(lengths) / STRIDE).cast("int") - 1)), lambda k: F.slice(lengths, k * STRIDE + 1, F.lit(STRIDE)))
    totals = F.transform(strides, lambda s: F.aggregate(s, zero, lambda a, x: a + x))
    bases = F.aggregate(totals, F.array(zero), lambda a, x: F.concat(a, F.array(F.element_at(a, -1) + x)))
    return F.flatten(
        F.transform(
            F.arrays_zip(strides.alias("s"), F.slice(bases, 1, F.size(strides)).alias("b")),
            lambda z: F.slice(F.aggregate(z["s"], F.array(z["b"]), lambda a, x: F.concat(a, F.array(F.element_at(a, -1) + x))), F.lit(1), F.size(z["s"])),
        )
    )


def format_conversations(turns: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """``(conv_id, turn, role, text)`` to ``(conv_id, n_blocks, formatted, loss_spans)``."""
    rows = turns.select("conv_id", F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"))
    sorted_ = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("ts"))
    ts = F.col("ts")
    pieces = F.transform(
        ts,
        lambda t, i: F.struct(
            F.when((i == 0) | (F.get(ts, i - 1)["role"] != t["role"]), F.concat(F.lit(OPEN), escape(t["role"]), F.lit(NAMED))).otherwise(F.lit(NEXT)).alias("before"),
            escape(t["text"]).alias("body"),
            F.when((i == F.size(ts) - 1) | (F.get(ts, i + 1)["role"] != t["role"]), F.lit(END)).otherwise(F.lit("")).alias("after"),
            (t["role"] == loss_role).alias("loss"),
        ),
    )
    out = sorted_.select("conv_id", pieces.alias("p"))
    p = F.col("p")
    size = F.transform(p, lambda x: (F.octet_length(x["before"]) + F.octet_length(x["body"]) + F.octet_length(x["after"])).cast("long"))
    out = out.select("conv_id", "p", _starts(size).alias("at"))
    spans = F.transform(
        F.filter(F.arrays_zip(p.alias("p"), F.col("at").alias("at")), lambda z: z["p"]["loss"]),
        lambda z: F.struct(
            (z["at"] + F.octet_length(z["p"]["before"])).alias("start"),
            (z["at"] + F.octet_length(z["p"]["before"]) + F.octet_length(z["p"]["body"])).alias("end"),
        ),
    )
    return out.select(
        "conv_id",
        F.size(F.filter(p, lambda x: x["after"] != "")).cast("long").alias("n_blocks"),
        F.array_join(F.transform(p, lambda x: F.concat(x["before"], x["body"], x["after"])), "").alias("formatted"),
        spans.alias("loss_spans"),
    )


def read_turns(formatted: Column) -> Column:
    """The rows of a formatted conversation: array<struct<role, text>>."""
    blocks = F.filter(F.split(formatted, r"<\|turn:"), lambda b: b != "")

    def rows(block: Column) -> Column:
        role = F.substring_index(block, NAMED, 1)
        # the block without its role, the mark after it and the end mark
        body = F.substring(block, F.length(role) + F.lit(len(NAMED) + 1), F.length(block) - F.length(role) - F.lit(len(NAMED) + len(END)))
        return F.transform(F.split(body, r"<\|next\|>"), lambda x: F.struct(unescape(role).alias("role"), unescape(x).alias("text")))

    return F.flatten(F.transform(blocks, rows))


def read_loss(formatted: Column, spans: Column) -> Column:
    """The unescaped text under the loss mask, joined by nothing."""
    raw = formatted.cast("binary")
    return F.array_join(F.transform(spans, lambda s: unescape(F.decode(F.substring(raw, (s["start"] + 1).cast("int"), (s["end"] - s["start"]).cast("int")), "UTF-8"))), "")


def read_back(chats: DataFrame) -> DataFrame:
    """What the formatted conversations hold, for checking against their rows."""
    got = chats.select("conv_id", "n_blocks", "formatted", read_turns(F.col("formatted")).alias("rows"), read_loss(F.col("formatted"), F.col("loss_spans")).alias("loss"))
    digest = F.sha2(F.array_join(F.transform("rows", lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n"))), "").cast("binary"), 256)
    return got.select(
        "conv_id",
        F.size("rows").cast("long").alias("n_turns"),
        digest.alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
        "n_blocks",
    )
