"""Chat training examples in budgeted windows, with DataFrame operations only (operator 6).

A conversation becomes windows of whole turns.  Prefix sums of the turns' token counts choose the
spans.  A window starts at the first turn not yet shown.  Windows after the first repeat the system turn and up to
``history`` turns that precede their span, as far as ``history_budget`` tokens go and the first new turn still fits; then the
span runs on while all that the window shows, repeats included, stays within the budget.  So no window passes the budget unless the system
turn and one new turn alone do.  Repeated turns are marked as such and stay outside the loss, so each assistant turn is a target once.

A turn's tokens are counted by the pattern ``TOKEN`` (pieces of up to four letters or three digits, other marks one by one)
and three for the turn's own marks, which a regular expression counts inside the JVM.

Template: ``<|turn|>role<|text|>text<|end|>``; a repeated turn opens with ``<|again|>``.
Inside roles and texts a backslash is doubled and ``<|`` becomes ``<\\|``, so none of the control
strings can occur in content, and :func:`read_back` undoes it exactly.

Defined results: null text and null role are empty; turns sort by ``turn`` (null first), then role and text,
so ties and repeated rows keep a fixed order and are all kept; a null ``conv_id`` is one
conversation; other columns are ignored; an empty table gives no rows.  A conversation's digest needs all
its turns in order, so one conversation is one row of arrays; its windows hold no more.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TURN, AGAIN, TEXT, END = "<|turn|>", "<|again|>", "<|text|>", "<|end|>"
BUDGET, HISTORY, HISTORY_BUDGET = 512, 2, 128
TOKEN, MARKS = r"\p{L}{1,4}|\p{N}{1,3}|[^\x09-\x0D\x20\p{L}\p{N}]", 3


def escape(c: Column) -> Column:
    return F.replace(F.replace(c, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescape(c: Column) -> Column:
    return F.replace(F.replace(c, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def tokens(c: Column) -> Column:
    """Tokens of a turn's text, its marks included."""
    return (F.regexp_count(c, F.lit(TOKEN)) + MARKS).cast("long")


def windows(
    turns: DataFrame,
    budget: int = BUDGET,
    history: int = HISTORY,
    history_budget: int = HISTORY_BUDGET,
    conv_col: str = "conv_id",
    turn_col: str = "turn",
    role_col: str = "role",
    text_col: str = "text",
) -> DataFrame:
    """``conv_id, window, first_turn, n_turns, formatted, loss``; ``loss`` lists (start, length) in code points of ``formatted``."""
    rows = turns.select(
        F.col(conv_col).alias("conv_id"),
        F.col(turn_col).alias("turn"),
        F.coalesce(F.col(role_col), F.lit("")).alias("role"),
        F.coalesce(F.col(text_col), F.lit("")).alias("text"),
    )
    # sums of the tokens before each turn, by one sorted pass; the exchange by conversation serves the collection too
    order = Window.partitionBy("conv_id").orderBy(F.col("turn").asc_nulls_first(), "role", "text")
    rows = rows.withColumn("tokens", tokens(F.col("text"))).withColumns({"i": F.row_number().over(order), "sum": F.sum("tokens").over(order.rowsBetween(Window.unboundedPreceding, 0))})
    item = F.struct("i", "role", "text", "tokens", (F.col("sum") - F.col("tokens")).alias("before"))
    conv = rows.groupBy("conv_id").agg(F.array_sort(F.collect_list(item)).alias("t"))
    n = F.size("t")
    first = F.get("t", F.lit(0))

    def repeated(i: Column) -> Column:
        """(turns of history, tokens of all repeats) of a window that starts at turn ``i``."""

        def cost(k: Column) -> Column:
            past = F.get("t", i)["before"] - F.get("t", i - k)["before"]
            system = F.when((first["role"] == "system") & (i > k), first["tokens"]).otherwise(F.lit(0))
            return F.struct(k.alias("k"), (past + system).alias("cost"), past.alias("past"))

        each = F.transform(F.sequence(F.lit(0), F.least(F.lit(history), i)), cost)
        fits = F.filter(each, lambda x: (x["k"] == 0) | ((x["past"] <= F.lit(history_budget)) & (x["cost"] + F.get("t", i)["tokens"] <= F.lit(budget))))
        return F.when(i > 0, F.array_max(fits)).otherwise(F.struct(F.lit(0).alias("k"), F.lit(0).cast("long").alias("cost"), F.lit(0).cast("long").alias("past")))

    conv = conv.withColumn("again", F.transform(F.sequence(F.lit(0), n - 1), repeated))
    # a new span starts where repeats and span together would pass the budget
    start0 = F.struct(F.lit(0).alias("at"), F.array(F.lit(0)).alias("starts"))

    def step(a: Column, i: Column) -> Column:
        shown = F.get("again", a["at"])["cost"] + F.get("t", i)["before"] + F.get("t", i)["tokens"] - F.get("t", a["at"])["before"]
        return F.when((shown > F.lit(budget)) & (i > a["at"]), F.struct(i.alias("at"), F.concat(a["starts"], F.array(i)).alias("starts"))).otherwise(a)

    conv = conv.withColumn("starts", F.aggregate(F.sequence(F.lit(0), n - 1), start0, step, lambda a: a["starts"]))
    spans = conv.select("conv_id", "t", "again", "starts", F.posexplode("starts").alias("window", "lo"))
    spans = spans.withColumn("hi", F.coalesce(F.get("starts", F.col("window") + 1), n))
    spans = spans.withColumn("from", F.col("lo") - F.get("again", F.col("lo"))["k"]).withColumn("system", (F.col("lo") > 0) & (first["role"] == "system"))
    again = F.when(F.col("system") & (F.col("from") > 0), F.slice("t", 1, 1)).otherwise(F.slice("t", 1, 0))
    shown = F.concat(
        F.transform(again, lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text"), F.lit(True).alias("again"))),
        F.transform(F.slice("t", F.col("from") + 1, F.col("lo") - F.col("from")), lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text"), F.lit(True).alias("again"))),
        F.transform(F.slice("t", F.col("lo") + 1, F.col("hi") - F.col("lo")), lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text"), F.lit(False).alias("again"))),
    )
    parts = F.transform(
        shown,
        lambda x: F.struct(
            F.concat(F.when(x["again"], F.lit(AGAIN)).otherwise(F.lit(TURN)), escape(x["role"]), F.lit(TEXT)).alias("head"),
            escape(x["text"]).alias("body"),
            ((x["role"] == "assistant") & ~x["again"]).alias("target"),
        ),
    )
    spans = spans.withColumn("parts", parts)
    mark0 = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,length:int>>").alias("loss"))

    def place(a: Column, p: Column) -> Column:
        body = a["at"] + F.length(p["head"])
        span = F.array(F.struct(body.alias("start"), F.length(p["body"]).alias("length")))
        return F.struct((body + F.length(p["body"]) + len(END)).alias("at"), F.when(p["target"], F.concat(a["loss"], span)).otherwise(a["loss"]).alias("loss"))

    return spans.select(
        "conv_id",
        "window",
        F.col("lo").alias("first_turn"),
        (F.col("hi") - F.col("lo")).alias("n_turns"),
        F.array_join(F.transform("parts", lambda p: F.concat(p["head"], p["body"], F.lit(END))), "").alias("formatted"),
        F.aggregate("parts", mark0, place, lambda a: a["loss"]).alias("loss"),
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """``conv_id, n_turns, turns, loss_text, formatted_chars`` parsed from the windows' text and loss spans alone.

    ``turns`` are (role, text) of all turns that are not repeats, in order; ``loss_text`` is the unescaped text under
    the loss mask, windows in order.
    """
    pieces = F.split("formatted", r"<\|(?=turn\|>|again\|>)", -1)
    fresh = F.filter(pieces, lambda p: p.startswith("turn|>"))
    cut = len("turn|>") + 1

    def turn(p: Column) -> Column:
        rest = F.substring(p, F.lit(cut), F.length(p) - len("turn|>") - len(END))
        at = F.locate(TEXT, rest)
        return F.struct(unescape(F.substring(rest, F.lit(1), at - 1)).alias("role"), unescape(F.substring(rest, at + len(TEXT), F.length(rest))).alias("text"))

    per = formatted.select(
        "conv_id",
        "window",
        F.transform(fresh, turn).alias("turns"),
        F.array_join(F.transform("loss", lambda s: unescape(F.substring(F.col("formatted"), s["start"] + 1, s["length"]))), "").alias("loss_text"),
        F.length("formatted").cast("long").alias("chars"),
    )
    all_ = per.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("window", "turns", "loss_text"))).alias("w"), F.sum("chars").alias("formatted_chars"))
    turns = F.flatten(F.transform("w", lambda x: x["turns"]))
    return all_.select("conv_id", F.size(turns).cast("long").alias("n_turns"), turns.alias("turns"), F.array_join(F.transform("w", lambda x: x["loss_text"]), "").alias("loss_text"), "formatted_chars")
