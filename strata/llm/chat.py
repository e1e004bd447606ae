"""Chat formatting into windows of a token budget.

Turns become marked pieces of text. Prefix sums of their tokens, taken in two levels so
that no conversation is summed in one task, cut each conversation into spans of whole
turns: a turn that lies within one stretch of the capacity belongs to that stretch's
span, and one that lies across a border joins the span it reaches into if that still
fits, and else is a span alone. Each later window repeats the conversation's system turn
and a limited history before its own turns. Repeated turns are outside the loss mask, so
every assistant text is a target once.

A turn's tokens are those that a column of the caller gives for its text (a tokenizer's
count, as `token_counts` makes it) and a quarter of its marks' bytes; without such a column
they are an estimate, a quarter of its bytes.

The template marks a turn as `### role: text </turn>`. Backslash, `#` and `<` in texts
(and `:` in roles) become two characters that begin with a backslash, so no text can
hold a mark, and undoing it is exact.

Only DataFrame functions are used.

Defined results: a null text or role counts as empty; turns are ordered by turn, then
role, then text, null turns last; repeated rows are turns of their own; a null conv_id
is a conversation like any other; a turn over the budget is a window of its own that is
marked over_budget; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from strata.llm.common import materialize

END = "</turn>\n"
#: Turns that are numbered and summed together.
STRETCH = 1024


def escape(c: Column, role: bool = False) -> Column:
    for char, code in (("\\", "\\b"), ("#", "\\h"), ("<", "\\l"), *(((":", "\\c"),) if role else ())):
        c = F.replace(c, F.lit(char), F.lit(code))
    return c


def unescape(c: Column) -> Column:
    for char, code in ((":", "\\c"), ("<", "\\l"), ("#", "\\h"), ("\\", "\\b")):
        c = F.replace(c, F.lit(code), F.lit(char))
    return c


def _pieces(turns: DataFrame, tokens_column: str | None = None) -> DataFrame:
    role, text = (F.coalesce(F.col(c), F.lit("")) for c in ("role", "text"))
    head = F.concat(F.lit("### "), escape(role, True), F.lit(": "))
    body = escape(text)
    counted = F.col(tokens_column).cast("long") if tokens_column else F.lit(None).cast("long")
    t = turns.select("conv_id", F.col("turn").cast("long").alias("turn"), role.alias("role"), text.alias("text"), head.alias("head"), body.alias("body"), counted.alias("counted"))
    piece = F.concat("head", "body", F.lit(f" {END}"))
    marks = F.ceil((F.octet_length("head") + len(END) + 1) / 4)
    return t.select(
        "conv_id", "turn", "role", "text", piece.alias("piece"), F.length("head").alias("at"), F.length("body").alias("long"),
        F.coalesce(F.col("counted") + marks, F.ceil(F.octet_length(piece) / 4)).cast("long").alias("tokens"), F.coalesce(F.floor(F.col("turn") / STRETCH), F.lit(1 << 60)).alias("stretch"),
    )


def _placed(p: DataFrame) -> DataFrame:
    """With `pos`, the number of turns before it in its conversation, and `start`, the number of their tokens."""
    w = Window.partitionBy("conv_id", "stretch").orderBy(F.asc_nulls_last("turn"), "role", "text").rowsBetween(Window.unboundedPreceding, 0)
    local = p.withColumn("pos", F.count("*").over(w) - 1).withColumn("start", F.sum("tokens").over(w) - F.col("tokens"))
    sums = p.groupBy("conv_id", "stretch").agg(F.count("*").alias("n"), F.sum("tokens").alias("s"))
    before = Window.partitionBy("conv_id").orderBy("stretch").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select(F.col("conv_id").alias("c"), F.col("stretch").alias("k"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("n0"), F.coalesce(F.sum("s").over(before), F.lit(0)).alias("s0"))
    j = local.join(offsets, F.col("conv_id").eqNullSafe(F.col("c")) & (F.col("stretch") == F.col("k")))
    return j.withColumn("pos", F.col("pos") + F.col("n0")).withColumn("start", F.col("start") + F.col("s0")).drop("c", "k", "n0", "s0", "turn", "text", "stretch")


def windows(turns: DataFrame, budget: int = 2048, history_turns: int = 2, history_tokens: int = 256, tokens_column: str | None = None) -> DataFrame:
    """One row per window: conv_id, window (ascending in a conversation), text, n_turns, n_repeated (how many
    of them, from the first, are repeated), tokens, over_budget and loss_spans, an array of (start, len) in code points.
    Where `tokens_column` is null or not given, a turn's tokens are estimated from its bytes."""
    placed = materialize(_placed(_pieces(turns, tokens_column)))
    system = placed.filter("role = 'system'").groupBy(F.col("conv_id").alias("c")).agg(F.min(F.struct("pos", "tokens", "piece")).alias("system"))
    same = F.col("conv_id").eqNullSafe(F.col("c"))
    room = F.greatest(F.lit(budget - history_tokens) - F.coalesce(F.col("system.tokens"), F.lit(0)), F.lit(1))
    t = placed.join(system.select("c", F.struct("system.pos", "system.tokens").alias("system")), same, "left").withColumn("room", room)
    t = t.withColumn("first_bin", F.floor(F.col("start") / F.col("room"))).withColumn("bin", F.floor((F.col("start") + F.col("tokens") - 1) / F.col("room")))
    across = F.col("first_bin") < F.col("bin")
    inside = F.sum(F.when(~across, F.col("tokens")).otherwise(0)).over(Window.partitionBy("conv_id", "bin"))
    alone = across & (F.col("tokens") + inside > F.col("room"))
    t = t.withColumn("window", F.col("bin") * 2 + F.when(alone, 0).otherwise(1))
    t = t.select("conv_id", "pos", "start", "tokens", "piece", "at", F.when(F.col("role") == "assistant", F.col("long")).otherwise(0).alias("long"), "window", F.col("system.pos").alias("system_pos"))
    t = materialize(t)

    part = F.struct(F.col("pos"), F.col("piece"), F.col("tokens"), F.col("at"), F.col("long"))
    own = t.select("conv_id", "window", F.lit(True).alias("new"), part.alias("p"))
    first = t.groupBy("conv_id", "window").agg(F.min("pos").alias("first"), F.min("start").alias("from"), F.first("system_pos").alias("system_pos"))
    masked = lambda pos, piece, tokens: F.struct(pos.alias("pos"), piece.alias("piece"), tokens.alias("tokens"), F.lit(0).alias("at"), F.lit(0).alias("long"))
    back = first.filter("first > 0").select(F.col("conv_id").alias("c"), "window", "from", "system_pos", F.explode(F.sequence(F.greatest(F.col("first") - history_turns, F.lit(0)), F.col("first") - 1)).alias("wanted"))
    plain = t.select("conv_id", "pos", "start", "piece", "tokens")
    history = plain.join(back, same & (F.col("pos") == F.col("wanted"))).filter((F.col("from") - F.col("start") <= history_tokens) & ~F.coalesce(F.col("pos") == F.col("system_pos"), F.lit(False)))
    history = history.select("conv_id", "window", F.lit(False).alias("new"), masked(F.col("pos"), F.col("piece"), F.col("tokens")).alias("p"))
    later = first.filter("first > system_pos").join(system, same)
    repeated = later.select("conv_id", "window", F.lit(False).alias("new"), masked(F.lit(-1).cast("long"), F.col("system.piece"), F.col("system.tokens")).alias("p"))

    w = own.unionByName(history).unionByName(repeated).groupBy("conv_id", "window").agg(F.sort_array(F.collect_list("p")).alias("p"), F.count_if(~F.col("new")).alias("n_repeated"))
    nothing = F.array().cast("array<struct<start:int,len:int>>")

    def add(acc, x):
        span = F.array(F.struct((acc["at"] + x["at"]).cast("int").alias("start"), x["long"].cast("int").alias("len")))
        return F.struct((acc["at"] + F.length(x["piece"])).cast("int").alias("at"), F.when(x["long"] > 0, F.concat(acc["out"], span)).otherwise(acc["out"]).alias("out"))

    spans = F.aggregate("p", F.struct(F.lit(0).alias("at"), nothing.alias("out")), add, lambda a: a["out"])
    tokens = F.aggregate("p", F.lit(0).cast("long"), lambda a, x: a + x["tokens"])
    w = w.select("conv_id", "window", F.array_join("p.piece", "").alias("text"), F.size("p").cast("long").alias("n_turns"), "n_repeated", tokens.alias("tokens"), spans.alias("loss_spans"))
    return w.withColumn("over_budget", F.col("tokens") > budget)


def read_back(w: DataFrame) -> DataFrame:
    """What windows say, by window: conv_id, window, n_turns (new ones), turns (role, newline, text, newline of
    each new turn), loss (all text under the mask, without escapes) and chars."""
    parts = F.split("text", END)
    new = F.slice(parts, (F.col("n_repeated") + 1).cast("int"), F.greatest((F.col("n_turns") - F.col("n_repeated")).cast("int"), F.lit(0)))

    def turn(p):
        head = F.length(F.regexp_extract(p, r"(?s)^### (.*?): ", 0))
        role = F.substring(p, F.lit(5), head - 6)
        text = F.substring(p, head + 1, F.length(p) - head - 1)
        return F.concat(unescape(role), F.lit("\n"), unescape(text), F.lit("\n"))

    loss = F.transform("loss_spans", lambda s: unescape(F.substring(F.col("text"), s["start"] + 1, s["len"])))
    return w.select("conv_id", "window", (F.col("n_turns") - F.col("n_repeated")).alias("n_turns"), F.array_join(F.transform(new, turn), "").alias("turns"), F.array_join(loss, "").alias("loss"), F.length("text").cast("long").alias("chars"))
