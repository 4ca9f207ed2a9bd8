"""Chat formatting: a role automaton, a declarative template, and text segments with loss flags.

Only DataFrame functions are used. A conversation becomes one row, because its formatted text is one
value; rows of different conversations never meet in one task's memory.

Defined results: null text is empty; a null role is the empty role (never trained on); turns are ordered by
(turn, role, text) with nulls first, so ties and repeated rows have one order and are all kept; rows with
a null conversation id form one conversation; an empty table gives no rows. Only the named columns of the input are
read, so extra columns cannot clash.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .state import let


@dataclass(frozen=True)
class ChatTemplate:
    """What stands around a turn, which roles are trained on, and which role may follow which.

    ``escapes`` holds (character, code letter): inside texts the character is written as a backslash and
    the letter, and a backslash as two, so no control string can occur in a text. ``role_escapes`` applies to
    role names besides.
    """

    opens: str = "### "
    names_end: str = "\n"
    closes: str = "</turn>\n"
    trained: tuple[str, ...] = ("assistant",)
    escapes: tuple[tuple[str, str], ...] = (("<", "l"), ("#", "h"))
    role_escapes: tuple[tuple[str, str], ...] = (("\n", "n"),)
    start: str = "start"
    moves: tuple[tuple[str, str, str], ...] = field(
        default=(
            ("start", "system", "briefed"),
            ("start", "user", "asked"),
            ("briefed", "user", "asked"),
            ("asked", "assistant", "answered"),
            ("answered", "user", "asked"),
        )
    )
    accepting: tuple[str, ...] = ("answered",)

    def __post_init__(self):
        coded = {c for c, _ in self.escapes}
        for control in (self.opens.strip(), self.closes.strip()):
            if not coded & set(control):
                raise ValueError(f"no escaped character in the control string {control!r}")
        if self.names_end not in {c for c, _ in self.role_escapes}:
            raise ValueError("the end of a role name must be escaped in role names")


def escape(text: Column, codes: tuple[tuple[str, str], ...]) -> Column:
    """Write every coded character as backslash and letter; reversible."""
    out = F.replace(text, F.lit("\\"), F.lit("\\\\"))
    for char, letter in codes:
        out = F.replace(out, F.lit(char), F.lit("\\" + letter))
    return out


def unescape(text: Column, codes: tuple[tuple[str, str], ...]) -> Column:
    """Undo :func:`escape`: pairs of backslashes are cut first, so each rest holds only code letters."""

    def plain(part: Column) -> Column:
        for char, letter in codes:
            part = F.replace(part, F.lit("\\" + letter), F.lit(char))
        return part

    return F.array_join(F.transform(F.split(text, r"\\\\", -1), plain), "\\")


def turn_automaton(roles: Column, template: ChatTemplate) -> Column:
    """struct(state, bad_at): the state after the roles, and the index of the first turn that no move allows (or null)."""
    moves = F.create_map(*[F.lit(x) for a, b, c in template.moves for x in (f"{a}\n{b}", c)])
    begin = F.struct(F.lit(template.start).alias("state"), F.lit(0).alias("at"), F.lit(None).cast("int").alias("bad_at"))

    def step(acc: Column, role: Column) -> Column:
        to = F.try_element_at(moves, F.concat(acc["state"], F.lit("\n"), role))
        return F.struct(
            F.coalesce(to, F.lit("rejected")).alias("state"),
            (acc["at"] + 1).alias("at"),
            F.coalesce(acc["bad_at"], F.when(to.isNull(), acc["at"])).alias("bad_at"),
        )

    return F.aggregate(roles, begin, step, lambda acc: F.struct(acc["state"].alias("state"), acc["bad_at"].alias("bad_at")))


def format_chats(turns: DataFrame, template: ChatTemplate = ChatTemplate(), conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """(conv_id, n_turns, valid, bad_turn, segments, formatted): one row per conversation.

    ``segments`` is an array of (text, loss) in order; joined they are ``formatted``. ``valid`` says that the
    roles follow the template's automaton and end in an accepting state; ``bad_turn`` is the index of the first turn out of order. Conversations out
    of order are formatted all the same.
    """
    codes, names = template.escapes, template.escapes + template.role_escapes
    one = F.struct(F.col(turn).alias("turn"), F.coalesce(F.col(role), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    grouped = turns.select(F.col(conv).alias("conv_id"), one.alias("one")).groupBy("conv_id").agg(F.sort_array(F.collect_list("one")).alias("turns"))

    def pieces(t: Column) -> Column:
        head = F.concat(F.lit(template.opens), escape(t["role"], names), F.lit(template.names_end))
        part = lambda text, loss: F.struct(text.alias("text"), loss.alias("loss"))
        return F.array(part(head, F.lit(False)), part(escape(t["text"], codes), t["role"].isin(*template.trained)), part(F.lit(template.closes), F.lit(False)))

    judged = grouped.select("conv_id", "turns", turn_automaton(F.transform("turns", lambda t: t["role"]), template).alias("fsm"), F.flatten(F.transform("turns", pieces)).alias("segments"))
    return judged.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        (F.col("fsm.bad_at").isNull() & F.col("fsm.state").isin(*template.accepting)).alias("valid"),
        F.col("fsm.bad_at").alias("bad_turn"),
        "segments",
        F.array_join(F.transform("segments", lambda s: s["text"]), "").alias("formatted"),
    )


def read_turns(formatted: Column, template: ChatTemplate = ChatTemplate()) -> Column:
    """array of (role, text), parsed back from a formatted conversation."""
    codes, names = template.escapes, template.escapes + template.role_escapes
    closes = "".join(f"\\x{ord(c):02x}" for c in template.closes)
    pieces = F.filter(F.split(formatted, closes, -1), lambda p: p != "")

    def turn(piece: Column) -> Column:
        body = F.substring(piece, len(template.opens) + 1, 2**31 - 1)
        at = F.instr(body, template.names_end)
        return F.struct(unescape(F.left(body, at - 1), names).alias("role"), unescape(F.substring(body, at + F.lit(len(template.names_end)), F.lit(2**31 - 1)), codes).alias("text"))

    return F.transform(pieces, turn)


def read_loss(segments: Column, template: ChatTemplate = ChatTemplate()) -> Column:
    """All text under the loss mask, unescaped, in order."""
    return F.array_join(F.transform(F.filter(segments, lambda s: s["loss"]), lambda s: unescape(s["text"], template.escapes)), "")


def chat_digests(chats: DataFrame, template: ChatTemplate = ChatTemplate()) -> DataFrame:
    """Digest columns read back from formatted conversations."""
    turns = read_turns(F.col("formatted"), template)
    told = let(turns, lambda ts: F.struct(F.size(ts).cast("long").alias("n"), F.array_join(F.transform(ts, lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "").alias("said")))
    read = chats.select("conv_id", told.alias("told"), read_loss(F.col("segments"), template).alias("loss"), F.length("formatted").cast("long").alias("formatted_chars"), "valid", "bad_turn")
    return read.select(
        "conv_id",
        F.col("told.n").alias("n_turns"),
        F.sha2(F.col("told.said").cast("binary"), 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"),
        "formatted_chars",
        "valid",
        "bad_turn",
    )
