"""Chat formatting by event-sourced reconstruction.

DataFrame functions only.  A log holds events of conversations in sequence:
``message`` opens a message, ``delta`` appends to it, ``edit`` replaces its
text, ``regenerate`` starts it anew and takes back all later messages, and
``delete`` removes it.  The fold leaves the final messages, which are rendered
with a template whose control strings cannot occur inside texts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# The template's control strings and the escapes of the characters they begin with.
TURN, END = "<|turn|>", "<|end|>\n"
ESCAPES = [("~", "~0"), ("<", "~1"), ("[", "~2"), ("\n", "~3")]


def escaped(text: Column, name: bool = False) -> Column:
    """``text`` without any character that begins a control string; a name has no line break either."""
    for plain, code in ESCAPES if name else ESCAPES[:3]:
        text = F.replace(text, F.lit(plain), F.lit(code))
    return text


def unescaped(text: Column, name: bool = False) -> Column:
    for plain, code in reversed(ESCAPES if name else ESCAPES[:3]):
        text = F.replace(text, F.lit(code), F.lit(plain))
    return text


def fold_events(events: DataFrame) -> DataFrame:
    """(conv_id, turn, role, text): the final messages of a log (conv_id, seq, turn, kind, role, text).

    ``turn`` names a message and gives its place.  A message, an edit and a
    regeneration start its text anew, a delta goes on, and deltas without an
    open message open one, after a deletion too.  A regeneration takes back what
    was said in later turns up to its seq.  The role is the last that was named
    since the message was opened.  A null kind is a message, a null text empty.
    Events of one turn and equal seq are ordered by kind, role and text.
    Conversations are folded each on its own, those with a null id together; an
    empty log has no messages.
    """
    log = events.select("conv_id", "seq", "turn", F.coalesce("kind", F.lit("message")).alias("kind"), "role", F.coalesce("text", F.lit("")).alias("text"))
    before = Window.partitionBy("conv_id").orderBy("turn").rangeBetween(Window.unboundedPreceding, -1)
    log = log.withColumn("cut", F.max(F.when(F.col("kind") == "regenerate", F.col("seq"))).over(before)).where("cut IS NULL OR seq > cut")
    message = Window.partitionBy("conv_id", "turn")
    log = log.withColumn("k", F.row_number().over(message.orderBy("seq", "kind", "role", "text")))
    log = log.withColumn("gone", F.max(F.when(F.col("kind") == "delete", F.col("k"))).over(message)).where("gone IS NULL OR k > gone")
    log = log.withColumn("start", F.max(F.when(F.col("kind").isin("message", "edit", "regenerate"), F.col("k"))).over(message))
    parts = F.array_sort(F.collect_list(F.when(F.col("start").isNull() | (F.col("k") >= F.col("start")), F.struct("k", "text"))))
    folded = log.groupBy("conv_id", "turn").agg(parts.alias("parts"), F.max_by("role", F.when(F.col("role").isNotNull(), F.col("k"))).alias("role"))
    return folded.select("conv_id", "turn", "role", F.array_join(F.transform("parts", lambda p: p["text"]), "").alias("text"))


def render(messages: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """One row for each conversation: conv_id, formatted, mask.

    ``mask`` is run-length coded over the code points of ``formatted``: head,
    body and foot of each turn, with ``loss`` true for the bodies of ``loss_role``.
    A null role is the empty name, a null text an empty text.  A conversation is
    one row by its nature; nothing else is gathered.
    """
    one = messages.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    head = F.concat(F.lit(TURN), escaped(F.col("role"), True), F.lit("\n"))
    body = escaped(F.col("text"))
    run = lambda n, loss: F.struct(n.cast("long").alias("n"), loss.alias("loss"))
    runs = F.array(run(F.length(head), F.lit(False)), run(F.length(body), F.col("role") == loss_role), run(F.lit(len(END)), F.lit(False)))
    made = one.select("conv_id", F.struct("turn", "role", F.concat(head, body, F.lit(END)).alias("segment"), runs.alias("runs")).alias("s"))
    whole = made.groupBy("conv_id").agg(F.array_sort(F.collect_list("s")).alias("turns"))
    return whole.select("conv_id", F.array_join(F.transform("turns", lambda t: t["segment"]), "").alias("formatted"), F.flatten(F.transform("turns", lambda t: t["runs"])).alias("mask"))


def read_back(rendered: DataFrame) -> DataFrame:
    """conv_id, formatted, turns (role, text) and loss_text, from ``formatted`` and ``mask`` alone."""
    split = F.split("formatted", r"<\|turn\|>")
    segments = F.slice(split, F.lit(2), F.greatest(F.size(split) - 1, F.lit(0)))

    def parsed(segment: Column, i: Column) -> Column:
        name = F.substring_index(segment, "\n", 1)
        head = F.element_at("mask", (3 * i + 1).cast("int"))["n"] - len(TURN)
        run = F.element_at("mask", (3 * i + 2).cast("int"))
        body = F.substr(segment, F.length(name) + 2, F.length(segment) - F.length(name) - 1 - len(END))
        masked = F.when(run["loss"], unescaped(F.substr(segment, (head + 1).cast("int"), run["n"].cast("int"))))
        return F.struct(unescaped(name, True).alias("role"), unescaped(body).alias("text"), masked.alias("loss"))

    turns = rendered.select("conv_id", "formatted", F.transform(segments, parsed).alias("turns"))
    return turns.select("conv_id", "formatted", "turns", F.array_join(F.transform("turns", lambda t: t["loss"]), "").alias("loss_text"))


def digests(read: DataFrame) -> DataFrame:
    """Counts and digests of what ``read_back`` gives."""
    told = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return read.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(told, 256).alias("turns_sha256"),
        F.length("loss_text").cast("long").alias("loss_chars"),
        F.sha2("loss_text", 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


def table_as_log(conversations: DataFrame) -> DataFrame:
    """A table of whole messages (conv_id, turn, role, text) as the log of a session that ends in them.

    An answer is first drafted and talked about, then regenerated and streamed
    in two deltas; any other message is mistyped, edited and gone on with, and
    followed by a message that is deleted.  Rows of equal turn follow each other
    by role and text.  The messages have even turns.
    """
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    placed = conversations.select("conv_id", (2 * F.row_number().over(order)).cast("long").alias("place"), "role", F.coalesce("text", F.lit("")).alias("text"))
    half = F.floor(F.length("text") / 2).cast("int")
    head, tail = F.substring(F.col("text"), F.lit(1), half), F.substring(F.col("text"), half + 1, F.length("text"))
    none, aside = F.lit(None).cast("string"), F.lit(1)

    def event(number: int, kind: str, role: Column, text: Column, later: Column | None = None) -> Column:
        place = F.col("place") + (0 if later is None else later)
        return F.struct((8 * F.col("place") + number).alias("seq"), place.alias("turn"), F.lit(kind).alias("kind"), role.alias("role"), text.alias("text"))

    answer = F.array(
        event(0, "message", F.col("role"), F.concat(F.lit("draft "), tail)),
        event(1, "delta", none, head),
        event(2, "message", F.lit("user"), F.lit("once more"), aside),
        event(3, "regenerate", F.col("role"), F.lit("")),
        event(4, "delta", none, head),
        event(5, "delta", none, tail),
    )
    other = F.array(
        event(0, "message", F.col("role"), F.concat(tail, head)),
        event(1, "edit", none, head),
        event(2, "delta", none, tail),
        event(3, "message", F.lit("assistant"), F.lit("gone"), aside),
        event(4, "delete", none, none, aside),
    )
    return placed.select("conv_id", F.explode(F.when(F.col("role") == "assistant", answer).otherwise(other)).alias("e")).select("conv_id", "e.*")
