"""Chat formatting: a state machine over roles and a declarative template, in DataFrame functions only.

A template lists, per role, the string that opens a turn and whether its text is trained on, and the
strings that begin a conversation and close a turn. Each conversation becomes segments (text, loss):
control strings without loss, turn texts with the role's flag. Texts are escaped so that no control
string can occur inside one: the escape character is doubled, and it is put after the first character
of every control string. Removing it again restores the text exactly.

The machine reads the roles in turn order. A missing transition marks the conversation invalid at that
turn; the conversation is still formatted, since the caller decides what to do with it.

Cases: turns are ordered by turn, then role, then text (nulls first), so ties and repeated rows have a
fixed order and all are kept; null text and null role are empty strings (an invalid transition for the
role); rows with a null conversation id form one conversation; empty tables give empty results. A
conversation is one row of the result and so must fit in a row.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Template:
    """Declarative description of a chat format and of the allowed order of roles."""

    begin: str = "<s>"
    close: str = "</s>"
    opens: tuple[tuple[str, str], ...] = (("system", "[SYS]"), ("user", "[INST]"), ("assistant", "[/INST]"))
    other: tuple[str, str] = ("[ROLE]", "[/ROLE]")
    trained: tuple[str, ...] = ("assistant",)
    start: str = "start"
    moves: tuple[tuple[str, str], ...] = (("start", "system"), ("start", "user"), ("system", "user"), ("user", "assistant"), ("assistant", "user"))
    ends: tuple[str, ...] = ("assistant",)
    escape: str = "\\"
    more_controls: tuple[str, ...] = field(default=("<<SYS>>", "<</SYS>>"))

    def controls(self) -> list[str]:
        return [self.begin, self.close, *(o for _, o in self.opens), *self.other, *self.more_controls]

    def check(self) -> None:
        """Refuse templates whose output could not be read back."""
        opens = [o for _, o in self.opens] + [self.other[0]]
        if any(len(c) < 2 or self.escape in c for c in self.controls()):
            raise ValueError("control strings need two characters and no escape character")
        if any(a != b and b.startswith(a) for a in opens for b in opens) or len({*opens}) < len(opens):
            raise ValueError("no opening string may begin another")


def _java(text: str) -> str:
    return re.sub(r"([\\\[\](){}.*+?^$|/<>-])", r"\\\1", text).replace(r"\<", "<").replace(r"\>", ">").replace(r"\/", "/").replace(r"\-", "-")


def escaped(text: Column, t: Template) -> Column:
    mark = _java(t.escape)
    doubled = F.regexp_replace(text, mark, (mark + mark).replace("$", r"\$"))
    return F.regexp_replace(doubled, f"(?s)(?=(?:{'|'.join(map(_java, t.controls()))}))(.)", "$1" + mark)


def unescaped(text: Column, t: Template) -> Column:
    mark = _java(t.escape)
    return F.regexp_replace(text, f"(?s){mark}(.)", "$1")


def turn_segments(turn: Column, t: Template) -> Column:
    """Segments of one turn: opening string, text, closing string."""
    segment = lambda text, loss: F.struct(text.alias("text"), loss.alias("loss"))
    opening = F.concat(F.lit(t.other[0]), escaped(turn["role"], t), F.lit(t.other[1]))
    for role, text in reversed(t.opens):
        opening = F.when(turn["role"] == role, F.lit(text)).otherwise(opening)
    return F.array(segment(opening, F.lit(False)), segment(escaped(turn["text"], t), turn["role"].isin(*t.trained)), segment(F.lit(t.close), F.lit(False)))


def order_error(turns: Column, t: Template) -> Column:
    """Number of the first turn that the machine refuses (the count of turns for a wrong end), or null."""
    allowed = F.array(*(F.lit(f"{a}\n{b}") for a, b in t.moves))
    first = F.struct(F.lit(t.start).alias("state"), F.lit(0).alias("at"), F.lit(None).cast("int").alias("bad"))

    def step(acc: Column, turn: Column) -> Column:
        fits = F.array_contains(allowed, F.concat_ws("\n", acc["state"], turn["role"]))
        return F.struct(turn["role"].alias("state"), (acc["at"] + 1).alias("at"), F.coalesce(acc["bad"], F.when(~fits, acc["at"])).alias("bad"))

    def finish(acc: Column) -> Column:
        return F.coalesce(acc["bad"], F.when(~acc["state"].isin(*t.ends), acc["at"]))

    return F.aggregate(turns, first, step, finish)


def format_chats(rows: DataFrame, template: Template = Template(), conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """(conv_id, n_turns, valid, bad_turn, formatted, segments) with one row per conversation."""
    template.check()
    blank = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    turn = F.struct(F.col(turn_col).alias("turn"), blank(role_col).alias("role"), blank(text_col).alias("text"))
    chats = rows.select(F.col(conv_col).alias("_conv"), turn.alias("_turn")).groupBy("_conv").agg(F.sort_array(F.collect_list("_turn")).alias("_turns"))
    begin = F.array(F.struct(F.lit(template.begin).alias("text"), F.lit(False).alias("loss")))
    segments = F.concat(begin, F.flatten(F.transform("_turns", lambda x: turn_segments(x, template))))
    bad = order_error(F.col("_turns"), template)
    made = chats.select("_conv", F.size("_turns").cast("long").alias("n_turns"), bad.alias("bad_turn"), segments.alias("segments"))
    text = F.array_join(F.transform("segments", lambda s: s["text"]), "")
    return made.select(F.col("_conv").alias(conv_col), "n_turns", F.col("bad_turn").isNull().alias("valid"), "bad_turn", text.alias("formatted"), "segments")


def read_back(formatted: Column, template: Template = Template()) -> Column:
    """Turns (role, text) parsed from a formatted conversation."""
    body = F.substring(formatted, len(template.begin) + 1, 2**31 - 1)
    pieces = F.filter(F.split(body, _java(template.close)), lambda p, i: p != "")

    def parse(piece: Column) -> Column:
        head = len(template.other[0])
        cut = F.position(F.lit(template.other[1]), piece)
        role = unescaped(F.substring(piece, F.lit(head + 1), cut - head - 1), template)
        text = F.substring(piece, cut + len(template.other[1]), F.length(piece))
        for name, opening in reversed(template.opens):
            begins = piece.startswith(opening)
            role = F.when(begins, F.lit(name)).otherwise(role)
            text = F.when(begins, F.substring(piece, F.lit(len(opening) + 1), F.length(piece))).otherwise(text)
        return F.struct(role.alias("role"), unescaped(text, template).alias("text"))

    return F.transform(pieces, parse)


def digest(made: DataFrame, template: Template = Template(), conv_col: str = "conv_id") -> DataFrame:
    """Figures read back from the output: turns from the formatted text, trained text from the loss flags."""
    turns = F.transform(read_back(F.col("formatted"), template), lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n")))
    loss = F.array_join(F.transform(F.filter("segments", lambda s: s["loss"]), lambda s: unescaped(s["text"], template)), "")
    return made.select(
        conv_col,
        F.size(read_back(F.col("formatted"), template)).cast("long").alias("n_turns"),
        F.sha2(F.array_join(turns, ""), 256).alias("turns_sha256"),
        F.length(loss).cast("long").alias("loss_chars"),
        F.sha2(loss, 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
        "valid",
    )


def oracle(template: Template = Template()) -> str:
    """DuckDB SQL for the digest of ``conversations`` with conversation -7 added."""
    q = lambda s: "'" + s.replace("'", "''") + "'"
    lengths = "CASE role " + " ".join(f"WHEN {q(r)} THEN {len(o)}" for r, o in template.opens)
    plain = " ".join(f"WHEN {q(a)} || chr(10) || {q(b)} THEN 1" for a, b in template.moves)
    quoted = lambda x: re.sub(r"([\[\]().*+?^$|\\])", r"\\\1", x)
    special = "|".join(map(quoted, template.controls()))
    other = sum(map(len, template.other))
    extra = f"length(regexp_replace({{0}}, '\\\\', '\\\\\\\\', 'g')) + len(regexp_extract_all({{0}}, {q(special)}))"
    return f"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
o AS (SELECT *, row_number() OVER w AS k, lag(role, 1, {q(template.start)}) OVER w AS prev FROM c WINDOW w AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text)),
g AS (SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY k) AS turns,
  coalesce(string_agg(CASE WHEN role IN ({', '.join(map(q, template.trained))}) THEN text END, '' ORDER BY k), '') AS loss,
  sum({lengths} ELSE {other} + {extra.format('role')} END + {len(template.close)} + {extra.format('text')}) + {len(template.begin)} AS chars,
  bool_and(CASE prev || chr(10) || role {plain} ELSE 0 END = 1) AND arg_max(role, k) IN ({', '.join(map(q, template.ends))}) AS valid FROM o GROUP BY conv_id)
SELECT conv_id, n_turns::BIGINT AS n_turns, sha256(turns) AS turns_sha256, length(loss)::BIGINT AS loss_chars, sha256(loss) AS loss_sha256, chars::BIGINT AS formatted_chars, valid FROM g
"""
