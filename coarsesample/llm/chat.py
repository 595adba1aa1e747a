"""Chat formatting in budgeted, turn-aligned windows, on built-in functions only.

A turn is written ``<s>`` role ``[INST]`` text ``</s>``. In roles and texts a backslash is doubled
and a backslash follows every ``<`` and ``[``, so no control string can arise inside a text, and the
reverse of that gives the text back.

A conversation's turns are cut into blocks of ``block_turns`` turn numbers, so that one endless
conversation is many bounded groups. Inside a block, prefix sums of the turns' costs choose the
windows: a window takes turns as long as the sum since its first turn fits the room left by the
system turn and the history. Later windows open with the system turn and up to ``history_turns``
turns before them, within ``history_budget``; what is repeated is outside the loss mask, which
covers each assistant text once. Turn tokens are counted by the caller, in the column named ``tokens``,
or estimated natively from the written turn.

Defined results: null text and null role count as empty; turns that share a number are ordered by
role, then text; null turn numbers come first; one turn over the room is a window of its own, never
cut; a system turn over half the budget is not repeated; an empty table gives no windows. Other
columns are not read. A block is bounded by its span of turn numbers: rows that repeat one number
without end would share a block.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

OPEN, BODY, CLOSE = "<s>", "[INST]", "</s>"


def escape(text: Column) -> Column:
    """No ``<`` or ``[`` is left without a backslash after it."""
    return F.regexp_replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), r"([<\[])", r"$1\\")


def unescape(text: Column) -> Column:
    """The reverse of escape()."""
    return F.regexp_replace(text, r"([<\[])\\|\\(\\)", "$1$2")


def cost(written: Column) -> Column:
    """Tokens of a written turn without a tokenizer: a piece for every six letters of a word, for three digits and for any other sign.

    That is how byte-pair vocabularies cut text on average; white space goes with the word after it.
    """
    return F.regexp_count(written, F.lit(r"\p{L}{1,6}|\p{N}{1,3}|[^\s\p{L}\p{N}]")).cast("long")


def _windows(turns: Column, room: Column) -> Column:
    """Window number of each turn, from prefix sums of the costs."""
    prefix = F.aggregate(turns, F.array(F.lit(0).cast("long")), lambda acc, t: F.concat(acc, F.array(F.element_at(acc, -1) + t["cost"])))
    start = F.struct(F.lit(0).alias("at"), F.lit(0).cast("long").alias("since"), F.array().cast("array<int>").alias("of"))

    def step(acc: Column, span: Column) -> Column:
        opens = (span["to"] - acc["since"] > room) & (span["from"] > acc["since"])
        at = F.when(opens, acc["at"] + 1).otherwise(acc["at"])
        return F.struct(at.alias("at"), F.when(opens, span["from"]).otherwise(acc["since"]).alias("since"), F.concat(acc["of"], F.array(at)).alias("of"))

    spans = F.zip_with(F.slice(prefix, F.lit(1), F.size(turns)), F.slice(prefix, F.lit(2), F.size(turns)), lambda a, b: F.struct(a.alias("from"), b.alias("to")))
    return F.aggregate(spans, start, step, lambda acc: acc["of"])


def _history(before: Column, most: int, budget: int) -> Column:
    """The last turns of ``before``, at most ``most``, as long as they fit ``budget``, in order."""
    kind = "array<struct<turn:bigint,role:string,text:string,written:string,cost:bigint>>"
    last = F.reverse(F.slice(before, F.greatest(F.size(before) - most, F.lit(0)) + 1, F.lit(most)))
    start = F.struct(F.array().cast(kind).alias("kept"), F.lit(0).cast("long").alias("sum"), F.lit(True).alias("open"))

    def step(acc: Column, t: Column) -> Column:
        fits = acc["open"] & (acc["sum"] + t["cost"] <= budget)
        return F.struct(F.when(fits, F.concat(F.array(t), acc["kept"])).otherwise(acc["kept"]).alias("kept"), F.when(fits, acc["sum"] + t["cost"]).otherwise(acc["sum"]).alias("sum"), fits.alias("open"))

    return F.aggregate(last, start, step, lambda acc: acc["kept"])


def format_windows(
    conversations: DataFrame,
    budget: int = 2048,
    history_turns: int = 2,
    history_budget: int = 256,
    block_turns: int = 128,
    conv: str = "conv_id",
    turn: str = "turn",
    role: str = "role",
    text: str = "text",
    tokens: str | None = None,
) -> DataFrame:
    """conv_id, block, window, formatted, n_context, n_new, tokens and loss_spans (start, length in code points)."""
    said = conversations.select(F.col(conv).alias("conv_id"), F.col(turn).cast("long").alias("turn"), F.coalesce(F.col(role), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text"), (F.col(tokens).cast("long") if tokens else F.lit(None).cast("long")).alias("cost"))
    said = said.withColumn("written", F.concat(F.lit(OPEN), escape(F.col("role")), F.lit(BODY), escape(F.col("text")), F.lit(CLOSE)))
    said = said.withColumn("cost", F.coalesce(F.col("cost"), cost(F.col("written")))).withColumn("block", F.coalesce(F.floor(F.col("turn") / block_turns), F.lit(-(1 << 62))))
    one = F.struct("turn", "role", "text", "written", "cost")
    blocks = said.groupBy("conv_id", "block").agg(F.sort_array(F.collect_list(one)).alias("turns"))

    # What a block needs from those before it is narrow: the system turn and the last few turns.
    spoken = F.filter("turns", lambda t: t["role"] != "system")
    edge = blocks.select(
        "conv_id",
        "block",
        F.slice(spoken, F.greatest(F.size(spoken) - history_turns, F.lit(0)) + 1, F.lit(history_turns)).alias("tail"),
        F.get(F.filter("turns", lambda t: t["role"] == "system"), 0).alias("system"),
    )
    in_order = Window.partitionBy("conv_id").orderBy("block")
    edge = edge.select(
        F.col("conv_id").alias("c"), F.col("block").alias("b"), F.lag("tail").over(in_order).alias("tail"), F.first("system", ignorenulls=True).over(in_order.rowsBetween(Window.unboundedPreceding, 0)).alias("system")
    )
    joined = blocks.join(edge, blocks["conv_id"].eqNullSafe(edge["c"]) & (blocks["block"] == edge["b"])).drop("c", "b")
    joined = joined.withColumn("system", F.when(F.col("system")["cost"] <= budget // 2, F.col("system")))
    room = F.lit(budget - history_budget) - F.coalesce(F.col("system")["cost"], F.lit(0))
    joined = joined.withColumn("of", _windows(F.col("turns"), room))
    opened = joined.select("*", F.explode(F.sequence(F.lit(0), F.array_max("of"))).alias("window"))
    opened = opened.withColumn("first", F.array_position("of", F.col("window")).cast("int"))
    opened = opened.withColumn("new", F.slice("turns", F.col("first"), F.size(F.filter("of", lambda w: w == F.col("window")))))
    before = F.concat(F.coalesce("tail", F.array().cast("array<struct<turn:bigint,role:string,text:string,written:string,cost:bigint>>")), F.filter(F.slice("turns", F.lit(1), F.col("first") - 1), lambda t: t["role"] != "system"))
    past = F.col("system").isNotNull() & (F.col("system") < F.col("new")[0])
    opened = opened.withColumn("context", F.concat(F.when(past, F.array("system")).otherwise(F.slice(F.array("system"), 1, 0)), _history(before, history_turns, history_budget)))
    whole = F.concat("context", "new")

    def step(acc: Column, t: Column) -> Column:
        head = F.char_length(F.concat(F.lit(OPEN), escape(t["role"]), F.lit(BODY)))
        length = F.char_length(t["written"])
        span = F.struct((acc["at"] + head).alias("start"), (length - head - len(CLOSE)).alias("length"))
        counts = (t["role"] == "assistant") & (acc["i"] >= F.size("context"))
        return F.struct((acc["i"] + 1).alias("i"), (acc["at"] + length).alias("at"), F.when(counts, F.concat(acc["spans"], F.array(span))).otherwise(acc["spans"]).alias("spans"))

    start = F.struct(F.lit(0).alias("i"), F.lit(0).alias("at"), F.array().cast("array<struct<start:int,length:int>>").alias("spans"))
    return opened.select(
        "conv_id",
        "block",
        "window",
        F.array_join(F.transform(whole, lambda t: t["written"]), "").alias("formatted"),
        F.size("context").alias("n_context"),
        F.size("new").alias("n_new"),
        F.aggregate(whole, F.lit(0).cast("long"), lambda acc, t: acc + t["cost"]).alias("tokens"),
        F.aggregate(whole, start, step, lambda acc: acc["spans"]).alias("loss_spans"),
    )


def read_back(windows: DataFrame) -> DataFrame:
    """The digests of each conversation, from the formatted windows alone.

    A digest of a conversation's whole text needs that text in one row; the windows do not.
    """
    fresh = F.slice(F.split("formatted", CLOSE), F.col("n_context") + 1, F.col("n_new"))
    parts = F.transform(fresh, lambda s: F.split(F.substr(s, F.lit(len(OPEN) + 1)), r"\[INST\]", 2))
    said = F.array_join(F.transform(parts, lambda p: F.concat(unescape(p[0]), F.lit("\n"), unescape(p[1]), F.lit("\n"))), "")
    under = F.array_join(F.transform("loss_spans", lambda s: unescape(F.substr(F.col("formatted"), s["start"] + 1, s["length"]))), "")
    one = windows.select("conv_id", F.struct("block", "window", said.alias("said"), under.alias("under")).alias("w"), "n_new", F.char_length("formatted").alias("chars"))
    whole = one.groupBy("conv_id").agg(F.sort_array(F.collect_list("w")).alias("w"), F.sum("n_new").alias("n_turns"), F.sum("chars").cast("long").alias("formatted_chars"))
    joined = whole.select("conv_id", "n_turns", "formatted_chars", F.array_join(F.transform("w", lambda w: w["said"]), "").alias("said"), F.array_join(F.transform("w", lambda w: w["under"]), "").alias("under"))
    return joined.select("conv_id", "n_turns", F.sha2(F.encode("said", "UTF-8"), 256).alias("turns_sha256"), F.char_length("under").cast("long").alias("loss_chars"), F.sha2(F.encode("under", "UTF-8"), 256).alias("loss_sha256"), "formatted_chars")
