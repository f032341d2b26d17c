"""Chat formatting with a declarative template, in DataFrame functions only.

A template names the marks around a turn, the control strings that texts must not contain, the transitions of the
role machine and the roles that carry loss. Control strings in texts are replaced by the escape character and a letter,
and the escape character itself by escape + "b", so that reading back is exact.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class ChatTemplate:
    head: str = "### "
    head_end: str = ": "
    tail: str = "</turn>\n"
    escape: str = "\\"
    #: control string -> letter after the escape character; the escape character itself takes "b"
    controls: tuple[tuple[str, str], ...] = (("</turn>", "t"), ("### ", "h"))
    #: escaped in role names only, so that the first head_end after a head ends the role
    role_controls: tuple[tuple[str, str], ...] = ((": ", "c"),)
    loss_roles: tuple[str, ...] = ("assistant",)
    start: str = "start"
    accept: tuple[str, ...] = ("assistant",)
    #: (state, role) -> state; anything else leads to "invalid", which is final
    moves: tuple[tuple[str, str, str], ...] = field(
        default=(
            ("start", "system", "system"), ("start", "user", "user"), ("system", "user", "user"),
            ("user", "assistant", "assistant"), ("assistant", "user", "user"),
        )
    )

    def guard(self, text: Column, role: bool = False) -> Column:
        out = F.replace(text, F.lit(self.escape), F.lit(self.escape + "b"))
        for plain, letter in self.controls + (self.role_controls if role else ()):
            out = F.replace(out, F.lit(plain), F.lit(self.escape + letter))
        return out

    def unguard(self, text: Column) -> Column:
        out = text
        for plain, letter in self.controls + self.role_controls:
            out = F.replace(out, F.lit(self.escape + letter), F.lit(plain))
        return F.replace(out, F.lit(self.escape + "b"), F.lit(self.escape))


def role_state(roles: Column, template: ChatTemplate) -> Column:
    """State of the role machine after an array of roles."""
    table = F.create_map(*[F.lit(x) for s, r, t in template.moves for x in (f"{s} {r}", t)])
    return F.aggregate(roles, F.lit(template.start), lambda s, r: F.coalesce(F.try_element_at(table, F.concat_ws(" ", s, r)), F.lit("invalid")))


def format_chats(rows: DataFrame, template: ChatTemplate = ChatTemplate(), conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """One row per conversation: conv, formatted, segments array<struct<text, loss>>, state, valid.

    Turns go by number, ties by role and text; nulls come first, and a null role or text is the empty string. Repeated
    rows are repeated turns. A null conversation id is a conversation of its own. No rows give no rows; other columns
    are ignored. valid tells whether the roles follow the machine to an accepting state; invalid ones are formatted too.
    """
    picked = rows.select(F.col(conv).alias("conv"), F.struct(F.col(turn).alias("turn"), F.coalesce(F.col(role), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text")).alias("m"))
    grouped = picked.groupBy("conv").agg(F.sort_array(F.collect_list("m")).alias("ms"))
    loss = lambda m: m["role"].isin(*template.loss_roles)
    parts = F.flatten(
        F.transform(
            "ms",
            lambda m: F.array(
                F.struct(F.concat(F.lit(template.head), template.guard(m["role"], True), F.lit(template.head_end)).alias("text"), F.lit(False).alias("loss")),
                F.struct(template.guard(m["text"]).alias("text"), loss(m).alias("loss")),
                F.struct(F.lit(template.tail).alias("text"), F.lit(False).alias("loss")),
            ),
        )
    )
    out = grouped.select("conv", role_state(F.col("ms.role"), template).alias("state"), parts.alias("segments"))
    return out.select(F.col("conv").alias(conv), F.concat_ws("", "segments.text").alias("formatted"), "segments", "state", F.col("state").isin(*template.accept).alias("valid"))


def parse_chats(formatted: Column, template: ChatTemplate = ChatTemplate()) -> Column:
    """array<struct<role, text>> read back from a formatted conversation."""
    cut = F.split(formatted, "\\Q" + template.tail + "\\E", -1)
    turns = F.slice(cut, F.lit(1), F.size(cut) - 1)
    at = lambda t: F.instr(t, template.head_end)
    return F.transform(
        turns,
        lambda t: F.struct(
            template.unguard(F.substring(t, F.lit(len(template.head) + 1), at(t) - 1 - len(template.head))).alias("role"),
            template.unguard(F.substring(t, at(t) + len(template.head_end), F.length(t))).alias("text"),
        ),
    )


def chat_digest(chats: DataFrame, template: ChatTemplate = ChatTemplate(), conv: str = "conv_id") -> DataFrame:
    """The contract's columns, all taken from the formatted strings and the loss flags."""
    back = chats.select(F.col(conv), "formatted", "segments", "state", "valid", parse_chats(F.col("formatted"), template).alias("turns"))
    lossy = template.unguard(F.concat_ws("", F.transform(F.filter("segments", lambda s: s["loss"]), lambda s: s["text"])))
    said = F.concat_ws("", F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))))
    return back.select(
        conv,
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said, 256).alias("turns_sha256"),
        F.length(lossy).cast("long").alias("loss_chars"),
        F.sha2(lossy, 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
        "state",
        "valid",
    )
