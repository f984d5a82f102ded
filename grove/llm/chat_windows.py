"""Chat formatting into budgeted windows.

Turn sizes in tokens are summed along each conversation; the running sum chooses
turn-aligned spans: a turn belongs to the window in whose share of the sum it ends.
A window holds the conversation's leading system turn again, up to ``history``
turns before it within ``history_budget`` tokens, and its own turns. Only
assistant turns are targets, each in one window: repeated ones carry no loss.

With a share of half the budget left by the system turn and history, a window stays
within ``budget`` unless one turn alone is larger than that share; such a turn is
kept whole.

Template. A turn is ``[INST role flag]text[/INST]</s>`` and a window starts with
``<s>``; the role is URL-encoded; the flag is ``n`` (new), ``h`` (repeated history) or
``s`` (repeated system turn). In texts a backslash is doubled and one is put after
the first character of ``<s>``, ``</s>``, ``[INST`` and ``[/INST``, so no text can look
like a mark and every text comes back exactly.

Only DataFrame functions run. Running sums are made in two levels, inside blocks of
``BLOCK`` turns and over the blocks' totals, so a conversation with a large part of
all rows is spread over tasks; history is found by an equality join on turn numbers.

Defined results: null text and role are empty; a null conversation id is one
conversation; turns with equal numbers go by role, then text; null turn numbers
come first.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from grove.session import cut

BLOCK = 1024
_MARKS = ("<s>", "</s>", "[INST", "[/INST")
#: One formatted turn: role, flag, escaped text.
TURN = r"(?s)\[INST (\S*) ([nhs])\](.*?)\[/INST\]</s>"


def escaped(text: Column) -> Column:
    out = F.replace(text, F.lit("\\"), F.lit("\\\\"))
    for m in _MARKS:
        out = F.replace(out, F.lit(m), F.lit(m[0] + "\\" + m[1:]))
    return out


def unescaped(text: Column) -> Column:
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def tokens_of(text: Column) -> Column:
    """Words and single signs: a size that needs no vocabulary."""
    return F.regexp_count(text, F.lit("[A-Za-z0-9]+|[^A-Za-z0-9\\x20\\x09-\\x0D]")).cast("long")


def numbered(rows: DataFrame) -> DataFrame:
    """(conv, turn, role, text, idx, size, upto): turn number from 0, tokens, and tokens so far."""
    r = rows.select(
        F.col("conv_id").cast("long").alias("conv"), F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")
    ).withColumn("size", tokens_of(F.col("text")) + 2)
    r = r.withColumn("block", F.coalesce(F.floor(F.col("turn") / BLOCK), F.lit(-(2**62))))
    inside = W.partitionBy("conv", "block").orderBy("turn", "role", "text").rowsBetween(W.unboundedPreceding, 0)
    r = cut(r.withColumn("k", F.row_number().over(W.partitionBy("conv", "block").orderBy("turn", "role", "text"))).withColumn("s", F.sum("size").over(inside)), "turns")
    before = W.partitionBy("conv").orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    totals = r.groupBy("conv", "block").agg(F.count("*").alias("rows"), F.sum("size").alias("sum"))
    offset = totals.select(
        F.col("conv").alias("_conv"), F.col("block").alias("_block"), F.coalesce(F.sum("rows").over(before), F.lit(0)).alias("k0"), F.coalesce(F.sum("sum").over(before), F.lit(0)).alias("s0")
    )
    return r.join(offset, F.col("conv").eqNullSafe(F.col("_conv")) & (F.col("block") == F.col("_block"))).select(
        "conv", "turn", "role", "text", (F.col("k") - 1 + F.col("k0")).alias("idx"), "size", (F.col("s") + F.col("s0")).alias("upto")
    )


def windows(rows: DataFrame, budget: int = 1024, history: int = 2, history_budget: int = 192) -> DataFrame:
    """(conv_id, window, formatted, n_tokens) from ``rows(conv_id, turn, role, text)``."""
    t = cut(numbered(rows), "numbered")
    share = (budget - history_budget) // 2
    system = t.where((F.col("idx") == 0) & (F.col("role") == "system")).select(F.col("conv").alias("_conv"), F.col("role").alias("s_role"), F.col("text").alias("s_text"), F.col("size").alias("s_size"))
    lead = system.select("_conv", "s_size")
    own = t.join(lead, F.col("conv").eqNullSafe(F.col("_conv")), "left").select(
        "conv", "idx", "role", "text", "size", "upto", F.floor((F.col("upto") - 1) / F.greatest(F.lit(share // 2).cast("long"), share - F.floor(F.coalesce("s_size", F.lit(0)) / 2))).alias("window")
    )
    own = cut(own, "own")
    first = own.groupBy("conv", "window").agg(F.min("idx").alias("first"), F.min(F.struct("idx", (F.col("upto") - F.col("size")).alias("base")))["base"].alias("base"))
    wanted = first.select(
        F.col("conv").alias("_conv"), F.col("window").alias("_window"), "base", F.explode(F.array(*[F.col("first") - d for d in range(1, history + 1)])).alias("_idx")
    ).where("_idx >= 0")
    past = (
        own.join(wanted, F.col("conv").eqNullSafe(F.col("_conv")) & (F.col("idx") == F.col("_idx")))
        .where(F.col("base") - F.col("upto") + F.col("size") <= history_budget)
        .where(~((F.col("idx") == 0) & (F.col("role") == "system")))
        .select("conv", F.col("_window").alias("window"), "idx", "role", "text", "size", F.lit("h").alias("flag"))
    )
    again = first.where("first > 0").join(system, F.col("conv").eqNullSafe(F.col("_conv"))).select("conv", "window", F.lit(-1).cast("long").alias("idx"), F.col("s_role").alias("role"), F.col("s_text").alias("text"), F.col("s_size").alias("size"), F.lit("s").alias("flag"))
    every = own.select("conv", "window", "idx", "role", "text", "size", F.lit("n").alias("flag")).unionByName(past).unionByName(again)
    turn = F.concat(F.lit("[INST "), F.url_encode("role"), F.lit(" "), F.col("flag"), F.lit("]"), escaped(F.col("text")), F.lit("[/INST]</s>"))
    return (
        every.select("conv", "window", "size", F.struct("idx", turn.alias("turn")).alias("t"))
        .groupBy("conv", "window")
        .agg(F.array_sort(F.collect_list("t")).alias("t"), F.sum("size").alias("n_tokens"))
        .select(F.col("conv").alias("conv_id"), "window", F.concat(F.lit("<s>"), F.array_join(F.transform("t", lambda x: x["turn"]), "")).alias("formatted"), "n_tokens")
    )


def turns_of(formatted: Column) -> Column:
    """The formatted window's turns as array<struct<role, flag, text, loss>>, read back."""
    roles, flags, texts = (F.regexp_extract_all(formatted, F.lit(TURN), F.lit(k)) for k in (1, 2, 3))
    return F.transform(
        F.arrays_zip(roles.alias("role"), flags.alias("flag"), texts.alias("text")),
        lambda x: F.struct(
            F.url_decode(x["role"]).alias("role"), x["flag"].alias("flag"), unescaped(x["text"]).alias("text"), ((x["flag"] == "n") & (F.url_decode(x["role"]) == "assistant")).alias("loss")
        ),
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """One row per conversation: its new turns and loss text, read from its windows."""
    new = formatted.select("conv_id", "window", F.length("formatted").cast("long").alias("chars"), F.filter(turns_of(F.col("formatted")), lambda x: x["flag"] == "n").alias("turns"))
    whole = new.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("window", "turns"))).alias("ws"), F.sum("chars").alias("formatted_chars"))
    turns = F.flatten(F.transform("ws", lambda w: w["turns"]))
    listed = whole.select("conv_id", turns.alias("turns"), "formatted_chars").withColumn("loss", F.array_join(F.transform(F.filter("turns", lambda x: x["loss"]), lambda x: x["text"]), ""))
    return listed.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("turns", lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n"))), "").cast("binary"), 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"),
        "formatted_chars",
    )
