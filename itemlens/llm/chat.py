"""Chat formatting in budgeted windows, by DataFrame functions alone.

Prefix sums of turn costs choose turn-aligned windows: a window takes turns as long as they fit its
budget together with what it repeats, the conversation's system turn (where it has one) and a
limited history before its own turns.  The loss covers the assistant texts among a window's own
turns, never repeated ones.  Only a single turn that is over the budget by itself makes a window
that is; it then repeats the system turn alone.

A token is four bytes of a turn as it is written, template and escapes included, rounded up for
each turn: no DataFrame function runs a tokenizer, and written bytes can be checked.

Template: `<role>text<end>` for each turn.  Inside roles and texts `~` is written `~0` and `<`
is written `~1` (and `>` as `~2` in roles), so no text can hold a mark and the writing can be undone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Tokens of a window, all that it repeats included, and of the history among them.
WINDOW_TOKENS, HISTORY_TOKENS = 1024, 256
TOKEN_BYTES = 4
TURN_END = "<end>"


def escaped(text: Column) -> Column:
    return F.replace(F.replace(F.coalesce(text, F.lit("")), F.lit("~"), F.lit("~0")), F.lit("<"), F.lit("~1"))


def escaped_role(role: Column) -> Column:
    return F.replace(escaped(role), F.lit(">"), F.lit("~2"))


def unescaped(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("~1"), F.lit("<")), F.lit("~0"), F.lit("~"))


def unescaped_role(role: Column) -> Column:
    return unescaped(F.replace(role, F.lit("~2"), F.lit(">")))


def _line(role: Column, text: Column) -> Column:
    return F.concat(F.lit("<"), role, F.lit(">"), text, F.lit(TURN_END))


def cost(role: Column, text: Column) -> Column:
    """Tokens of a turn as it is written."""
    return F.ceil(F.octet_length(_line(escaped_role(role), escaped(text))) / TOKEN_BYTES)


def spans(rows: DataFrame, budget: int, history: int) -> DataFrame:
    """(conv_id, window, first, last, start, system) from rows (conv_id, number, begin, cost, opens): own turns first..last.

    What is repeated begins at turn `start`, before it the system turn (turn 1) where `system` says
    so.  opens: whether a turn is the first and a system turn.
    """
    whole = Window.partitionBy("conv_id")
    recent = whole.orderBy("begin").rangeBetween(-history, 0)
    known = rows.withColumn("system", F.max(F.when(F.col("opens"), F.col("cost")).otherwise(0)).over(whole))
    # The turns of the last `history` tokens before a turn, without the system turn.
    start = F.greatest(F.min("number").over(recent), F.when(F.col("system") > 0, 2).otherwise(1))
    known = known.withColumn("start", F.least(start, F.col("number"))).withColumn("past", F.col("begin") - F.greatest(F.min("begin").over(recent), F.col("system")))
    fits = (F.col("number") > 1) & (F.col("system") + F.col("past") + F.col("cost") <= budget)
    room = F.when(F.col("number") == 1, budget).otherwise(budget - F.col("system") - F.when(fits, F.col("past")).otherwise(0))
    turn = F.struct(
        "number", (F.col("begin") + F.col("cost")).alias("end"), (F.col("begin") + F.greatest(F.col("cost"), room)).alias("limit"), F.when(fits, F.col("start")).otherwise(F.col("number")).alias("start")
    )
    folded = known.groupBy("conv_id").agg(F.sort_array(F.collect_list(turn)).alias("turns"), (F.max("system") > 0).alias("system"))
    opened = "array<struct<first: int, start: int>>"
    none = F.struct(F.lit(-1).cast("long").alias("limit"), F.array().cast(opened).alias("windows"))

    def step(state, t):
        fresh = F.struct(t["limit"].alias("limit"), F.concat(state["windows"], F.array(F.struct(t["number"].alias("first"), t["start"].alias("start"))).cast(opened)).alias("windows"))
        return F.when(t["end"] <= state["limit"], state).otherwise(fresh)

    cut = folded.select("conv_id", "system", F.size("turns").alias("n"), F.aggregate("turns", none, step)["windows"].alias("windows"))
    following = F.coalesce(F.get("windows", F.col("window") + 1)["first"] - 1, F.col("n"))
    each = cut.select("conv_id", "system", "n", "windows", F.posexplode("windows").alias("window", "w"))
    return each.select("conv_id", "window", F.col("w.first").alias("first"), following.alias("last"), F.col("w.start").alias("start"), (F.col("system") & (F.col("w.first") > 1)).alias("system"))


def windows(turns: DataFrame, budget: int = WINDOW_TOKENS, history: int = HISTORY_TOKENS) -> DataFrame:
    """(conv_id, window, formatted, fresh_from, turns_in, loss): windows of all conversations.

    turns: conv_id, turn, role, text.  Turns are ordered by turn, then role, then text (nulls first);
    null roles and texts are empty; repeated rows are turns of their own.  fresh_from: where the own
    turns start in `formatted`, in code points from 1 (system turn and history before it are
    repeats); loss: (start, length) of each trained text there.  Turns of a null conv_id form one
    conversation; a conversation's turn costs are folded in one row.  An empty table gives no rows.
    """
    rows = turns.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).withColumn("cost", cost(F.col("role"), F.col("text")))
    w = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    before = F.coalesce(F.sum("cost").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    placed = rows.withColumn("begin", before).withColumn("number", F.row_number().over(w))
    opens = (F.col("number") == 1) & (F.col("role") == "system")
    found = spans(placed.select("conv_id", "number", "begin", "cost", opens.alias("opens")), budget, history)
    held = F.concat(F.when(F.col("system"), F.array(F.lit(1))).otherwise(F.array().cast("array<int>")), F.sequence("start", "last"))
    homes = found.select(F.col("conv_id").alias("conv"), "window", "first", F.explode(held).alias("at"))
    met = placed.join(homes, F.col("conv_id").eqNullSafe(F.col("conv")) & (F.col("number") == F.col("at")))
    turn = F.struct("number", (F.col("number") >= F.col("first")).alias("fresh"), escaped_role(F.col("role")).alias("role"), escaped(F.col("text")).alias("text"))
    grouped = met.groupBy("conv_id", "window").agg(F.sort_array(F.collect_list(turn)).alias("turns"))
    line = lambda t: _line(t["role"], t["text"])
    old, new = F.filter("turns", lambda t: ~t["fresh"]), F.filter("turns", lambda t: t["fresh"])
    built = grouped.select("conv_id", "window", F.array_join(F.transform(old, line), "").alias("repeats"), new.alias("new"))
    empty = F.struct(F.col("head").alias("at"), F.array().cast("array<struct<start: int, length: int>>").alias("loss"))

    def step(state, t):
        text_at = state["at"] + F.length(t["role"]) + 2
        here = F.when(t["role"] == "assistant", F.array(F.struct(text_at.alias("start"), F.length(t["text"]).alias("length")))).otherwise(F.array())
        return F.struct((text_at + F.length(t["text"]) + len(TURN_END)).alias("at"), F.concat(state["loss"], here.cast("array<struct<start: int, length: int>>")).alias("loss"))

    return built.withColumn("head", F.length("repeats") + 1).select(
        "conv_id", "window", F.concat("repeats", F.array_join(F.transform("new", line), "")).alias("formatted"),
        F.col("head").alias("fresh_from"), F.size("new").alias("turns_in"), F.aggregate("new", empty, step)["loss"].alias("loss"),
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars from windows() alone."""
    fresh = F.substring("formatted", F.col("fresh_from"), F.length("formatted"))
    lines = F.slice(F.split(fresh, TURN_END), 1, F.col("turns_in"))
    parts = F.transform(lines, _turn_text)
    trained = F.transform("loss", lambda s: unescaped(F.substring(F.col("formatted"), s["start"], s["length"])))
    each = formatted.select(
        "conv_id", "window", "turns_in", F.array_join(parts, "").alias("turns"), F.array_join(trained, "").alias("trained"), F.length("formatted").cast("long").alias("chars")
    )
    grouped = each.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("window", "turns", "trained"))).alias("w"), F.sum("turns_in").alias("n_turns"), F.sum("chars").alias("formatted_chars"))
    text = lambda name: F.array_join(F.col("w")[name], "")
    return grouped.select(
        "conv_id", F.col("n_turns").cast("long").alias("n_turns"), F.sha2(text("turns"), 256).alias("turns_sha256"), F.length(text("trained")).cast("long").alias("loss_chars"),
        F.sha2(text("trained"), 256).alias("loss_sha256"), "formatted_chars",
    )


def _turn_text(line: Column) -> Column:
    """role, newline, text, newline of one `<role>text`."""
    role = F.substring_index(line, ">", 1)
    text = F.substring(line, F.length(role) + 2, F.length(line))
    return F.concat(unescaped_role(F.substring(role, F.lit(2), F.length(role))), F.lit("\n"), unescaped(text), F.lit("\n"))
