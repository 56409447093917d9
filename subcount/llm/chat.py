"""Chat formatting from event logs, with DataFrame functions only.

reconstruct() folds a log of events per conversation into final messages. Kinds: `message` (a whole turn),
`delta` (text added to a turn), `edit` (a new text for a turn) and `regenerate` (the turn starts anew, and
turns after it that were logged before are gone). The events of a turn are sorted by sequence and folded: its text is
that of the last event that isn't a delta with the deltas after it, its role the first one named. log() turns a
table of finished turns into such a log, with drafts, edits, regenerations and streamed pieces that must fold back to
the rows.

render() writes one string per conversation. A turn is `### role: text</turn>` and a line end. Inside roles
and texts a backslash goes before a backslash, before `#` after `#`, and between `<` and `/turn>` (roles:
before `:` too), so no text can hold a mark, and removing the escapes gives the text back. The loss mask
is one (skip, take, rest) per turn, in code points of that turn's stretch; take covers assistant texts.

Defined cases: null text is empty; null role is empty; a row that repeats is a turn of its own; rows of equal turn
number are ordered by role and text (their `copy` numbers); events of one sequence number are ordered by kind, role
and text; null conversation ids are one conversation, null turns one turn before the others; an empty table gives
no rows; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# Fixed marks of the template.
HEAD, COLON, TAIL = "### ", ": ", "</turn>\n"
_TEXT = r"\\|(?<=#)#|(?<=<)/(?=turn>)"
ASSISTANT = "assistant"


def escaped(text: Column, role: bool = False) -> Column:
    return F.regexp_replace(text, F.lit(_TEXT + "|:" * role), F.lit(r"\\$0"))


def unescaped(text: Column) -> Column:
    return F.regexp_replace(text, F.lit(r"(?s)\\(.)"), F.lit("$1"))


def log(conversations: DataFrame, piece: int = 256) -> DataFrame:
    """An event log of a table of finished turns: by the hash of a turn it is logged whole, as streamed deltas of
    `piece` characters, as a draft with an edit, or as a draft that is regenerated and streamed again."""
    text, role = F.coalesce("text", F.lit("")), F.coalesce("role", F.lit(""))
    within = Window.partitionBy("conv_id", "turn").orderBy("role", "text")
    rows = conversations.select("conv_id", "turn", role.alias("role"), text.alias("text")).withColumn("copy", F.row_number().over(within))
    event = lambda kind, said, who=F.lit(None).cast("string"): F.struct(F.lit(kind).alias("kind"), who.alias("role"), said.alias("text"))
    pieces = F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.floor((F.length("text") - 1) / piece).cast("int"))), lambda k: F.substr(F.col("text"), k * piece + 1, F.lit(piece)))
    streamed = F.transform(pieces, lambda p: event("delta", p))
    draft = event("message", F.reverse("text"), F.col("role"))
    how = F.pmod(F.xxhash64("conv_id", "turn", "copy"), F.lit(4))
    events = (
        F.when(how == 0, F.array(event("message", F.col("text"), F.col("role"))))
        .when(how == 1, F.concat(F.array(event("message", F.lit(""), F.col("role"))), streamed))
        .when(how == 2, F.array(draft, event("delta", F.lit(" ...")), event("edit", F.col("text"))))
        .otherwise(F.concat(F.array(draft, event("regenerate", F.lit(""))), streamed))
    )
    at = rows.select("conv_id", "turn", "copy", F.posexplode(events).alias("step", "e"))
    # a sequence in the order of turns, so a regeneration comes before all later turns
    return at.select("conv_id", F.struct("turn", "copy", "step").alias("seq"), "turn", "copy", "e.kind", "e.role", "e.text")


def reconstruct(events: DataFrame) -> DataFrame:
    """conv_id, turn, copy, seq, role, text: the final turns of a log (conv_id, seq, turn, kind, role, text, and
    copy where one turn number stands for several turns)."""
    copy = F.col("copy") if "copy" in events.columns else F.lit(0).alias("copy")
    e = events.select("conv_id", "seq", "turn", copy, "kind", "role", F.coalesce("text", F.lit("")).alias("text"))
    redo = e.where("kind = 'regenerate'").select(F.col("conv_id").alias("c"), F.col("turn").alias("t"), F.col("seq").alias("s"))
    redo = redo.groupBy("c", "t").agg(F.max("s").alias("s"))
    gone = F.col("conv_id").eqNullSafe(F.col("c")) & (F.col("turn") > F.col("t")) & (F.col("seq") < F.col("s"))
    said = F.sort_array(F.collect_list(F.struct("seq", "kind", "role", "text")))
    turns = e.join(redo, gone, "left_anti").groupBy("conv_id", "turn", "copy").agg(said.alias("said"))
    start = F.array_max(F.transform("said", lambda x, k: F.when(x["kind"] != "delta", k + 1).otherwise(1)))
    roles = F.filter("said", lambda x: x["role"].isNotNull())
    return turns.select(
        "conv_id",
        "turn",
        "copy",
        F.element_at("said", -1)["seq"].alias("seq"),
        F.get(roles, 0)["role"].alias("role"),
        F.array_join(F.transform(F.slice("said", start, F.size("said")), lambda x: x["text"]), "").alias("text"),
    )


def render(turns: DataFrame) -> DataFrame:
    """conv_id, formatted, mask: one row per conversation."""
    role, text = F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))
    copy = F.col("copy") if "copy" in turns.columns else F.lit(0).alias("copy")
    pieces = turns.select("conv_id", "turn", copy, "seq", role.alias("role"), text.alias("text")).select(
        "conv_id",
        F.struct(
            "turn",
            "copy",
            "seq",
            "role",
            "text",
            F.concat(F.lit(HEAD), escaped(F.col("role"), True), F.lit(COLON)).alias("head"),
            escaped(F.col("text")).alias("body"),
        ).alias("p"),
    )
    grouped = pieces.groupBy("conv_id").agg(F.sort_array(F.collect_list("p")).alias("ps"))

    def runs(p):
        head, body, loss = F.length(p["head"]), F.length(p["body"]), p["role"] == ASSISTANT
        return F.struct(
            F.when(loss, head).otherwise(head + body).cast("long").alias("skip"),
            F.when(loss, body).otherwise(0).cast("long").alias("take"),
            F.lit(len(TAIL)).cast("long").alias("rest"),
        )

    return grouped.select(
        "conv_id",
        F.array_join(F.transform("ps", lambda p: F.concat(p["head"], p["body"], F.lit(TAIL))), "").alias("formatted"),
        F.transform("ps", runs).alias("mask"),
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """conv_id, turns (role, text) and loss texts, from a rendered string and its mask alone."""
    cut = F.split("formatted", TAIL.replace("/", "\\/"), -1)
    stretch = F.slice(cut, F.lit(1), F.size(cut) - 1)
    pattern = r"(?s)^### ((?:[^:\\]++|\\.)*+): (.*)$"
    parsed = formatted.withColumn("stretches", stretch)
    return parsed.select(
        "conv_id",
        "formatted",
        F.transform(
            "stretches",
            lambda s: F.struct(
                unescaped(F.regexp_extract(s, pattern, 1)).alias("role"), unescaped(F.regexp_extract(s, pattern, 2)).alias("text")
            ),
        ).alias("turns"),
        F.zip_with("stretches", "mask", lambda s, m: unescaped(F.substr(s, (m["skip"] + 1).cast("int"), m["take"].cast("int")))).alias("loss"),
    )


def digests(formatted: DataFrame) -> DataFrame:
    back = read_back(formatted)
    turns = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join("loss", "")
    return back.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(turns.cast("binary"), 256).alias("turns_sha256"),
        F.length(loss).cast("long").alias("loss_chars"),
        F.sha2(loss.cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )
