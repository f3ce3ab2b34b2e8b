"""Chat formatting: conversations are folded from their event log, rendered, and can be read back exactly.

A log has one row per event: conversation, sequence number, the turn it concerns, its kind, role and text.

* ``message``: the turn's whole text; a later one of the same turn replaces it;
* ``delta``: appended to what the turn has so far;
* ``edit``: replaces the turn's text, the role stays unless given;
* ``regenerate``: starts the turn anew (its own text first, deltas follow) and discards all later turns that
  were written before it.

Events are folded turn by turn first, so that a long conversation is spread over tasks, then the turns of a
conversation are put in order and rendered.  Everything is DataFrame functions; no Python runs on executors.

Template: every turn is ``<s>role`` + newline + body + ``</s>``; the body of an assistant is its text, that of
any other role ``[INST] text [/INST]``.  Inside roles and texts, backslashes are doubled and a backslash is put
after the first character of each control string, which ``unescape`` undoes exactly; a newline in a role is
written in the same way.  The loss mask is a list of (start, length) in code points of the formatted string: the
escaped text of every assistant turn, without the marks around it.

Defined results: a null text or role is empty; events of equal sequence number are taken in order of kind, role
and text, identical ones once; a null turn or sequence number comes first; null conversation ids form one
conversation; an empty log gives no conversations.  In a table of finished turns every row is a turn of its own:
rows of one turn number stay side by side in order of role and text, and those without a number come last.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vertexlog.llm.common import let, once

#: Control strings of the template; fixed values.
CONTROLS = ("<s>", "</s>", "[INST]", "[/INST]")
END = "</s>"

#: Columns that place a turn in its conversation; a log has ``turn`` alone, rows of finished turns have all.
PLACE = ("late", "turn", "copy")


def escape(text: Column) -> Column:
    out = F.replace(text, F.lit("\\"), F.lit("\\\\"))
    for c in CONTROLS:
        out = F.replace(out, F.lit(c), F.lit(f"{c[0]}\\{c[1:]}"))
    return out


def unescape(text: Column) -> Column:
    out = text
    for c in CONTROLS:
        out = F.replace(out, F.lit(f"{c[0]}\\{c[1:]}"), F.lit(c))
    return F.replace(out, F.lit("\\\\"), F.lit("\\"))


def escape_role(role: Column) -> Column:
    return F.replace(escape(role), F.lit("\n"), F.lit("<\\n>"))


def unescape_role(role: Column) -> Column:
    """As ``unescape``; only a newline is written as ``<``, a single backslash, ``n>``."""
    return unescape(F.replace(role, F.lit("<\\n>"), F.lit("\n")))


def fold_turns(events: DataFrame, conv_col: str = "conv_id") -> DataFrame:
    """Log -> (conversation, turn, role, text, last, anew): each turn's final state and where it last changed."""
    blank = F.struct(F.lit("").alias("role"), F.lit("").alias("text"), F.lit(None).cast("bigint").alias("last"), F.lit(None).cast("bigint").alias("anew"))

    def apply(state: Column, e: Column) -> Column:
        text = F.coalesce(e["text"], F.lit(""))
        anew = e["kind"] == "regenerate"
        return F.struct(
            F.coalesce(F.nullif(e["role"], F.lit("")), state["role"]).alias("role"),
            F.when(e["kind"] == "delta", F.concat(state["text"], text)).otherwise(text).alias("text"),
            e["seq"].alias("last"),
            F.when(anew, e["seq"]).otherwise(state["anew"]).alias("anew"),
        )

    event = F.struct(F.col("seq").cast("bigint").alias("seq"), F.col("kind"), F.col("role"), F.col("text"))
    place = [c for c in PLACE if c in events.columns]
    grouped = events.groupBy(conv_col, *place).agg(F.array_sort(F.collect_set(event)).alias("e"))
    return grouped.select(conv_col, *place, F.aggregate("e", blank, apply).alias("s")).select(conv_col, *place, "s.*")


def running(sizes: Column, block: int = 1000) -> Column:
    """Sums of all sizes before each, in blocks, so that appending stays cheap for very many."""

    def before(part: Column, start: Column) -> Column:
        step = lambda a, n: F.struct((a["at"] + n).alias("at"), F.array_append(a["out"], a["at"]).alias("out"))
        return F.aggregate(part, F.struct(start.alias("at"), F.array().cast("array<bigint>").alias("out")), step, lambda a: a["out"])

    zero = F.lit(0).cast("bigint")
    starts = F.when(F.size(sizes) > 0, F.sequence(F.lit(1), F.size(sizes), F.lit(block))).otherwise(F.array().cast("array<int>"))
    blocks = F.transform(starts, lambda i: F.slice(sizes, i, F.lit(block)))
    totals = lambda b: before(F.transform(b, lambda p: F.aggregate(p, zero, lambda a, n: a + n)), zero)
    return let(blocks, lambda b: F.flatten(F.zip_with(b, totals(b), before)))


def render(turns: DataFrame, conv_col: str = "conv_id") -> DataFrame:
    """Folded turns -> (conversation, formatted, loss): one string per conversation and its loss mask."""
    turn = F.struct(*(c for c in PLACE if c in turns.columns), "last", "anew", "role", "text")
    written = "array<struct<head:string,body:string,loss:boolean>>"

    def live(all_turns: Column) -> Column:
        """Turns that no earlier turn's regeneration has discarded."""
        step = lambda a, t: F.struct(
            F.greatest(a["since"], t["anew"]).alias("since"),
            F.when(a["since"].isNull() | F.coalesce(t["last"] >= a["since"], F.lit(True)), F.array_append(a["kept"], _written(t))).otherwise(a["kept"]).alias("kept"),
        )
        return F.aggregate(all_turns, F.struct(F.lit(None).cast("bigint").alias("since"), F.array().cast(written).alias("kept")), step, lambda a: a["kept"])

    ordered = F.array_sort(F.collect_list(turn))
    kept = F.when(F.col("anew").isNull(), F.transform("t", _written)).otherwise(live(F.col("t")))
    made = once(turns.groupBy(conv_col).agg(ordered.alias("t"), F.max("anew").alias("anew")), "w", kept)
    sizes = F.transform("w", lambda x: (F.length(x["head"]) + F.length(x["body"]) + len(END)).cast("bigint"))
    mask = F.zip_with("w", running(sizes), lambda x, at: F.struct((at + F.length(x["head"])).alias("start"), F.length(x["body"]).cast("bigint").alias("length"), x["loss"].alias("loss")))
    loss = F.transform(F.filter(mask, lambda x: x["loss"]), lambda x: F.struct(x["start"].alias("start"), x["length"].alias("length")))
    return made.select(conv_col, F.array_join(F.transform("w", lambda x: F.concat(x["head"], x["body"], F.lit(END))), "").alias("formatted"), loss.alias("loss"))


def _written(t: Column) -> Column:
    """A turn as what stands before its text, its text, and whether that counts for the loss."""
    own = t["role"] == "assistant"
    head = F.concat(F.lit("<s>"), escape_role(t["role"]), F.lit("\n"), F.when(own, "").otherwise("[INST] "))
    return F.struct(head.alias("head"), F.concat(escape(t["text"]), F.when(own, "").otherwise(" [/INST]")).alias("body"), own.alias("loss"))


def masked(formatted: Column, loss: Column) -> Column:
    """Array of the unescaped texts under a loss mask, each cut from its own turn and not from the string's start."""

    def cut(turns: Column) -> Column:
        starts = running(F.transform(turns, lambda x: (F.length(x) + len(END)).cast("bigint")))
        at = F.zip_with(turns, starts, lambda x, i: F.struct(i.alias("at"), F.lit(0).alias("span"), x.alias("text"), F.lit(0).cast("bigint").alias("length")))
        spans = F.transform(loss, lambda x: F.struct(x["start"].alias("at"), F.lit(1).alias("span"), F.lit(None).cast("string").alias("text"), x["length"].alias("length")))
        return let(F.array_sort(F.concat(at, spans)), lambda row: F.filter(F.transform(row, lambda x, i: under(row, x, i)), lambda t: t.isNotNull()))

    def under(row: Column, x: Column, i: Column) -> Column:
        turn = F.get(row, i - 1)  # a span comes right behind the turn it lies in
        return F.when(x["span"] == 1, unescape(F.substring(turn["text"], (x["at"] - turn["at"] + 1).cast("int"), x["length"].cast("int"))))

    return let(F.split(formatted, END, -1), cut)


def read_back(formatted: Column) -> Column:
    """Array of (role, text) of a formatted conversation."""

    def one(piece: Column) -> Column:
        cut = F.locate("\n", piece)
        role = unescape_role(F.substring(piece, F.lit(4), cut - 4))
        body = F.substring(piece, cut + 1, F.length(piece))
        inner = F.substring(body, F.lit(8), F.length(body) - 15)
        return F.struct(role.alias("role"), unescape(F.when(role == "assistant", body).otherwise(inner)).alias("text"))

    pieces = F.split(formatted, "</s>", -1)
    return let(pieces, lambda p: F.transform(F.slice(p, 1, F.size(p) - 1), one))


def format_log(events: DataFrame, conv_col: str = "conv_id") -> DataFrame:
    """The whole operator: event log -> (conversation, formatted, loss)."""
    return render(fold_turns(events, conv_col), conv_col)


def rows_as_events(rows: DataFrame, conv_col: str = "conv_id") -> DataFrame:
    """A table of finished turns as a log of ``message`` events, one turn for each row."""
    turn = F.col("turn").cast("bigint")
    numbered = rows.select(conv_col, turn.isNull().alias("late"), turn.alias("turn"), turn.alias("seq"), F.lit("message").alias("kind"), "role", "text")
    beside = Window.partitionBy(conv_col, "turn").orderBy("role", "text")
    return numbered.withColumn("copy", F.row_number().over(beside))


def conversation_report(rows: DataFrame) -> DataFrame:
    """The contract's digest, taken from the formatted strings."""
    spark = rows.sparkSession
    hard = "</s>[INST] ok [/INST]"
    extra = spark.range(2).select(F.lit(-1).cast("bigint").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(hard).alias("text"))
    done = format_log(rows_as_events(rows.select("conv_id", "turn", "role", "text").unionByName(extra)))
    found = F.struct(read_back(F.col("formatted")).alias("t"), masked(F.col("formatted"), F.col("loss")).alias("l"))
    back = once(done, "b", found).select("conv_id", F.length("formatted").cast("bigint").alias("formatted_chars"), "b.t", "b.l")
    turns = F.array_join(F.transform("t", lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n"))), "")
    loss = F.array_join("l", "")
    return back.select(
        "conv_id",
        F.size("t").cast("bigint").alias("n_turns"),
        F.sha2(turns, 256).alias("turns_sha256"),
        F.length(loss).cast("bigint").alias("loss_chars"),
        F.sha2(loss, 256).alias("loss_sha256"),
        "formatted_chars",
    )
