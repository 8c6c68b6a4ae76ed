"""Chat formatting into budgeted windows.

Running sums of turn tokens place every turn; sums and comparisons alone choose turn-aligned spans that fit the budget.
Each span becomes one training window: the system turn, a limited tail of the span before it (repeated as context,
outside the loss), then the span's own turns, whose assistant texts are the targets. Each turn is new in one window.

Template: ``<s>[INST]role[/INST]text</s>`` for each turn. Inside role and text a backslash is doubled and one is put
after the first character of each control string, so no text can imitate a mark and the change can be undone.
Only DataFrame functions are used.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

OPEN, ROLE_END, CLOSE = "<s>[INST]", "[/INST]", "</s>"
#: The strings a text must not contain unescaped.
CONTROL = "<s>|</s>|\\[INST\\]|\\[/INST\\]"
#: Tokens the marks of one turn count for.
MARK_TOKENS = 8


def escaped(text: Column) -> Column:
    doubled = F.replace(text, F.lit("\\"), F.lit("\\\\"))
    return F.regexp_replace(doubled, f"(?=(?:{CONTROL}))(.)", "$1\\\\")


def unescaped(text: Column) -> Column:
    return F.regexp_replace(text, "\\\\(.)", "$1")


def default_tokens(text: Column) -> Column:
    """A tokeniser-free estimate: a quarter of the code points, rounded up, plus the marks."""
    return F.ceil(F.char_length(text) / 4).cast("long") + MARK_TOKENS


def placed_turns(turns: DataFrame, budget: int, history: int, tokens=default_tokens) -> DataFrame:
    """One row for each turn: conv_id, idx (from 0), role, text, tokens, before (tokens of earlier turns), span."""
    text, role = F.coalesce("text", F.lit("")), F.coalesce("role", F.lit(""))
    order = W.partitionBy("conv_id").orderBy(F.col("turn").asc_nulls_first(), "role", "text")
    rows = turns.select("conv_id", "turn", role.alias("role"), text.alias("text")).withColumn("tokens", tokens(F.col("text")))
    upto = order.rowsBetween(W.unboundedPreceding, 0)
    rows = rows.select("*", (F.row_number().over(order) - 1).alias("idx"), (F.sum("tokens").over(upto) - F.col("tokens")).alias("before"))
    place = W.partitionBy("conv_id").orderBy("idx")
    # What a window has for turns of its own: the system turn and the history are charged to the budget.
    system = F.coalesce(F.max(F.when((F.col("idx") == 0) & (F.col("role") == "system"), F.col("tokens"))).over(W.partitionBy("conv_id")), F.lit(0))
    rows = rows.withColumn("_half", F.greatest(F.floor((F.lit(budget - history) - system) / 2), F.lit(1)))
    half = F.col("_half")
    # Turns that start in the same half-budget interval share a span; a turn of more than half stands alone.
    interval, long_turn = F.floor(F.col("before") / half), F.col("tokens") > half
    starts = (F.lag(interval).over(place) != interval) | F.lag(long_turn).over(place) | long_turn
    rows = rows.withColumn("_starts", F.when(F.col("idx") == 0, 0).otherwise(F.coalesce(starts, F.lit(True)).cast("int")))
    return rows.withColumn("span", F.sum("_starts").over(place.rowsBetween(W.unboundedPreceding, 0)).cast("long")).drop("_starts", "_half")


def chat_windows(turns: DataFrame, budget: int = 1024, history: int = 256, tokens=default_tokens) -> DataFrame:
    """conv_id, window (from 0), formatted, segments, n_tokens.

    ``segments`` lists the window's turns in order: idx, kind (system, history, new), start and length of the escaped
    text in code points of ``formatted``, and loss (true for a new assistant turn). A null text or role counts as
    empty. Turns go by number, ties by role, then text; repeated rows are turns of their own. A leading system turn is
    repeated in every window. System turn, history and own turns of a window take at most ``budget`` tokens together; only
    where a single turn, or the system turn, takes more than that leaves does a window of that one turn exceed it, as turns are never cut. The history takes at
    most ``history``. A null conv_id is a conversation.
    Columns other than conv_id, turn, role and text are ignored. An empty table gives no windows.

    A conversation's turns pass through one task as a sorted stream with spill; only a window, whose size the
    budget bounds, is gathered.
    """
    rows = placed_turns(turns, budget, history, tokens)
    conv, span = W.partitionBy("conv_id"), W.partitionBy("conv_id", "span")
    rows = rows.select(
        "*",
        F.max("span").over(conv).alias("_last"),
        F.max(F.col("before") + F.col("tokens")).over(span).alias("_end"),
    )
    leads = (F.col("idx") == 0) & (F.col("role") == "system")
    kept = ~leads & (F.col("_end") - F.col("before") <= history) & (F.col("span") < F.col("_last"))
    use = lambda window, kind: F.struct(window.cast("long").alias("window"), F.lit(kind).alias("kind"))
    none = F.array().cast("array<struct<window:bigint,kind:string>>")
    uses = F.concat(
        F.array(use(F.col("span"), "new")),
        F.when(kept, F.array(use(F.col("span") + 1, "history"))).otherwise(none),
        F.when(leads & (F.col("_last") > 0), F.transform(F.sequence(F.lit(1).cast("long"), F.greatest(F.col("_last"), F.lit(1).cast("long"))), lambda w: use(w, "system"))).otherwise(none),
    )
    parts = rows.select(
        "conv_id",
        F.explode(uses).alias("use"),
        "idx",
        "tokens",
        F.concat(F.lit(OPEN), escaped(F.col("role")), F.lit(ROLE_END)).alias("head"),
        escaped(F.col("text")).alias("body"),
        (F.col("role") == "assistant").alias("target"),
    )
    piece = F.struct("idx", F.col("use.kind").alias("kind"), "head", "body", ((F.col("use.kind") == "new") & F.col("target")).alias("loss"))
    windows = parts.groupBy("conv_id", F.col("use.window").alias("window")).agg(
        F.array_sort(F.collect_list(piece)).alias("_parts"), F.sum("tokens").alias("n_tokens")
    )
    segment_type = "array<struct<idx:int,kind:string,start:bigint,length:bigint,loss:boolean>>"
    state = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast(segment_type).alias("out"))

    def lay(s: Column, p: Column) -> Column:
        start = s["at"] + F.char_length(p["head"])
        length = F.char_length(p["body"]).cast("long")
        seg = F.struct(p["idx"].alias("idx"), p["kind"].alias("kind"), start.alias("start"), length.alias("length"), p["loss"].alias("loss"))
        return F.struct((start + length + len(CLOSE)).alias("at"), F.concat(s["out"], F.array(seg)).alias("out"))

    return windows.select(
        "conv_id",
        "window",
        F.array_join(F.transform("_parts", lambda p: F.concat(p["head"], p["body"], F.lit(CLOSE))), "").alias("formatted"),
        F.aggregate("_parts", state, lay)["out"].alias("segments"),
        "n_tokens",
    )


def read_back(windows: DataFrame) -> DataFrame:
    """The digests of each conversation, from formatted windows alone.

    Marks are found again in the text: it is split at the turn ends, and each turn at its role mark. Of the turns so
    found, those whose segment is new count; under the loss mask, text is cut from ``formatted`` by its offsets.
    """
    seg = lambda i: F.element_at("segments", (i + 1).cast("int"))
    found = F.filter(F.split("formatted", CLOSE), lambda t: t != "")
    own = F.filter(F.transform(found, lambda t, i: F.struct(seg(i)["kind"].alias("kind"), t.alias("t"))), lambda x: x["kind"] == "new")
    role = lambda t: unescaped(F.regexp_extract(t, r"(?s)^<s>\[INST\](.*?)\[/INST\]", 1))
    body = lambda t: unescaped(F.regexp_extract(t, r"(?s)^<s>\[INST\].*?\[/INST\](.*)$", 1))
    turns = F.transform(own, lambda x: F.concat(role(x["t"]), F.lit("\n"), body(x["t"]), F.lit("\n")))
    masked = F.filter("segments", lambda s: s["loss"])
    loss = F.transform(masked, lambda s: unescaped(F.substring(F.col("formatted"), (s["start"] + 1).cast("int"), s["length"].cast("int"))))
    read = windows.select(
        "conv_id",
        "window",
        F.size(own).cast("long").alias("_n"),
        F.array_join(turns, "").alias("_turns"),
        F.array_join(loss, "").alias("_loss"),
        F.char_length("formatted").cast("long").alias("_chars"),
    )
    all_ = F.array_sort(F.collect_list(F.struct("window", "_turns", "_loss")))
    one = read.groupBy("conv_id").agg(
        F.sum("_n").alias("n_turns"), all_.alias("_all"), F.sum("_chars").alias("formatted_chars"), F.count(F.lit(1)).alias("n_windows")
    )
    joined = lambda field: F.array_join(F.transform("_all", lambda x: x[field]), "")
    return one.select(
        "conv_id",
        "n_turns",
        F.sha2(joined("_turns"), 256).alias("turns_sha256"),
        F.char_length(joined("_loss")).cast("long").alias("loss_chars"),
        F.sha2(joined("_loss"), 256).alias("loss_sha256"),
        "formatted_chars",
        "n_windows",
    )
