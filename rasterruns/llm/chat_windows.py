"""Chat formatting in budgeted windows, with DataFrame functions only.

A conversation's turns get prefix sums of their token counts.  What the budget
leaves beside the system turn and the history is the span: turns that lie
between the same two multiples of the span along the sums share a window, and a
turn that crosses a multiple has a window of its own.  Each window repeats the
leading system turn and, as far as the budget still allows, a limited history
of the turns just before it, so a window never exceeds the budget unless the
system turn and one turn alone do (with ``charged``, the default).  Repeated turns are context, outside the loss
mask, so each assistant text is under the mask once.

Template: a turn is ``<turn:n>`` (new) or ``<turn:c>`` (context), the role, a
newline, the text and ``</turn>`` with a newline.  In roles and texts ``&``,
``<`` and ``[`` become ``&a``, ``&l`` and ``&b`` (in roles a newline becomes
``&n``), which undoes itself and leaves no control string of any common
template inside a text.

Defined results: null roles and texts count as empty; null turns come first;
rows with equal turns stand in order of role, then text; null conversation ids
are one conversation; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Tokens of a window with all that it repeats, and of the history among them (at most HISTORY_TURNS turns).
BUDGET = 512
HISTORY_TOKENS = 128
HISTORY_TURNS = 2
#: Fixed values of the template.
OPEN_NEW, OPEN_CONTEXT, CLOSE = "<turn:n>", "<turn:c>", "</turn>\n"
ESCAPES = (("&", "&a"), ("<", "&l"), ("[", "&b"))


def _swap(text: Column, old: str, new: str) -> Column:
    return F.replace(text, F.lit(old), F.lit(new))


def escape(text: Column) -> Column:
    for plain, safe in ESCAPES:
        text = _swap(text, plain, safe)
    return text


def unescape(text: Column) -> Column:
    text = _swap(text, "&n", "\n")
    for plain, safe in reversed(ESCAPES):
        text = _swap(text, safe, plain)
    return text


def format_windows(turns: DataFrame, budget: int = BUDGET, history_tokens: int = HISTORY_TOKENS, history_turns: int = HISTORY_TURNS, charged: bool = True) -> DataFrame:
    """``turns(conv_id, turn, role, text)`` -> one row per window.

    ``charged``: what a window repeats is charged to its budget, which then
    holds.  Otherwise turns that start within the same half budget share a
    window and repeats come on top, so that a window may exceed ``budget``.

    Columns: conv_id, window (from 1), text, loss (array of start, length in
    characters), n_new, n_context, tokens.  One shuffle, by conversation; rows
    hold the turns of one window.
    """
    t = turns.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    t = t.select("conv_id", "turn", "role", "text", _swap(escape(F.col("role")), "\n", "&n").alias("safe_role"), escape(F.col("text")).alias("safe"))
    line = Window.partitionBy("conv_id").orderBy(F.col("turn").asc_nulls_first(), "role", "text")
    t = t.withColumn("pos", F.row_number().over(line))
    t = t.withColumn("is_system", (F.col("pos") == 1) & (F.col("role") == "system"))
    cost = (F.ceil(F.length("safe") / 4) + 4).cast("long")
    # the system turn is charged to every window apart from the sums
    t = t.withColumn("system", F.first(F.when(F.col("is_system"), cost).otherwise(F.lit(0))).over(line))
    t = t.withColumn("tokens", F.when(F.col("is_system"), F.lit(0)).otherwise(cost).cast("long"))
    t = t.withColumn("start", F.coalesce(F.sum("tokens").over(line.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    width = F.greatest(F.lit(budget - history_tokens) - F.col("system") if charged else F.lit(budget // 2), F.lit(1))
    t = t.withColumn("span", F.floor(F.col("start") / width))
    t = t.withColumn("crosses", F.lit(charged) & (F.col("tokens") > 0) & (F.floor((F.col("start") + F.col("tokens") - 1) / width) > F.col("span")))
    opens = (F.col("span") != F.lag("span").over(line)) | F.col("crosses") | F.lag("crosses").over(line)
    t = t.withColumn("opens", F.coalesce(opens, F.lit(True)).cast("int"))
    t = t.withColumn("win", F.sum("opens").over(line.rowsBetween(Window.unboundedPreceding, 0)).cast("int"))
    free = F.lit(budget) - F.col("system") - F.sum("tokens").over(Window.partitionBy("conv_id", "win"))
    t = t.withColumn("room", F.least(F.lit(history_tokens), free) if charged else F.lit(history_tokens))
    for k in range(1, history_turns + 1):
        t = t.withColumn(f"w{k}", F.lead("win", k).over(line)).withColumn(f"s{k}", F.lead("start", k).over(line)).withColumn(f"r{k}", F.lead("room", k).over(line))
    t = t.withColumn("last_win", F.max("win").over(Window.partitionBy("conv_id")))
    seen, repeats = F.col("win"), []
    for k in range(1, history_turns + 1):
        fits = (F.col(f"w{k}") > seen) & (F.col(f"s{k}") - F.col("start") <= F.col(f"r{k}"))
        repeats.append(F.when(fits, F.col(f"w{k}")))
        seen = F.greatest(seen, F.col(f"w{k}"))
    history = F.array_compact(F.array(*repeats)) if repeats else F.array().cast("array<int>")
    again = F.when(F.col("is_system"), F.when(F.col("last_win") > 1, F.sequence(F.lit(2), F.col("last_win"))).otherwise(F.array().cast("array<int>"))).otherwise(history)
    placed = t.withColumn("window", F.explode(F.concat(F.array("win"), again))).withColumn("is_new", F.col("window") == F.col("win"))
    head = F.concat(F.when(F.col("is_new"), F.lit(OPEN_NEW)).otherwise(F.lit(OPEN_CONTEXT)), F.col("safe_role"), F.lit("\n"))
    placed = placed.select("conv_id", "window", "pos", "is_new", (F.col("is_new") & (F.col("role") == "assistant")).alias("learn"), F.length(head).alias("head"), F.length("safe").alias("body"), F.concat(head, F.col("safe"), F.lit(CLOSE)).alias("piece"), F.when(F.col("is_system"), F.col("system")).otherwise(F.col("tokens")).alias("tokens"))
    inside = Window.partitionBy("conv_id", "window").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    placed = placed.withColumn("off", F.coalesce(F.sum(F.length("piece")).over(inside), F.lit(0)).cast("int"))
    parts = placed.groupBy("conv_id", "window").agg(F.array_sort(F.collect_list(F.struct("pos", "piece", "learn", (F.col("off") + F.col("head")).alias("start"), "body"))).alias("parts"), F.sum(F.col("is_new").cast("int")).cast("long").alias("n_new"), F.sum((~F.col("is_new")).cast("int")).cast("long").alias("n_context"), F.sum("tokens").alias("tokens"))
    text = F.array_join(F.transform("parts", lambda p: p["piece"]), "")
    loss = F.transform(F.filter("parts", lambda p: p["learn"]), lambda p: F.struct(p["start"].alias("start"), p["body"].alias("length")))
    return parts.select("conv_id", "window", text.alias("text"), loss.alias("loss"), "n_new", "n_context", "tokens")


def read_back(windows: DataFrame) -> DataFrame:
    """Parse formatted windows again: per window the new turns, unescaped, and the text under the mask.

    Columns: conv_id, window, said (array of ``role newline text``), learnt
    (array of texts), chars.
    """
    said = F.filter(F.split("text", "<turn:"), lambda x: x.startswith("n>"))
    said = F.transform(said, lambda x: unescape(F.substring(x, F.lit(3), F.length(x) - 2 - len(CLOSE))))
    learnt = F.transform("loss", lambda s: unescape(F.substring(F.col("text"), s["start"] + 1, s["length"])))
    return windows.select("conv_id", "window", said.alias("said"), learnt.alias("learnt"), F.length("text").alias("chars"))


def conversation_digests(windows: DataFrame) -> DataFrame:
    """Per conversation, from the formatted windows alone: counts and digests of turns and loss texts.

    A digest of a conversation needs its text in one row, so a conversation
    must fit in a row (2 GB); nothing else is gathered by conversation.
    """
    parts = read_back(windows).select("conv_id", F.struct("window", F.size("said").alias("n"), F.array_join(F.transform("said", lambda x: F.concat(x, F.lit("\n"))), "").alias("said"), F.array_join("learnt", "").alias("learnt")).alias("part"), "chars")
    whole = parts.groupBy("conv_id").agg(F.array_sort(F.collect_list("part")).alias("p"), F.sum("chars").cast("long").alias("formatted_chars"), F.count(F.lit(1)).alias("n_windows"))
    said = F.array_join(F.transform("p", lambda x: x["said"]), "")
    learnt = F.array_join(F.transform("p", lambda x: x["learnt"]), "")
    n = F.aggregate("p", F.lit(0).cast("long"), lambda a, x: a + x["n"])
    return whole.select("conv_id", n.alias("n_turns"), F.sha2(said, 256).alias("turns_sha256"), F.length(learnt).cast("long").alias("loss_chars"), F.sha2(learnt, 256).alias("loss_sha256"), "formatted_chars", "n_windows")
