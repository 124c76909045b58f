"""Operator 7: chat formatting by a finite-state machine over roles.

A declarative template gives each role its opening and closing mark and its loss flag. The
machine walks the turns of a conversation in order, checks each role against the allowed
moves, and emits text segments: mark, escaped text, mark. Control signs inside texts and
unknown role names are escaped with a backslash, so ``parse_turn`` gives back role and text.

Conversations are dealt by id and sorted by turn; the machine reads them as a stream and
keeps a state, not the turns, so a conversation of any length needs the same memory.

Edge cases: a null text is empty; a null role is the empty name, which like any role outside
the template gets the generic marks and makes the conversation invalid; null turns come first;
equal turns are ordered by role, then text; rows with a null conversation id form one
conversation; invalid conversations are formatted all the same and flagged; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkedrank.sources import read_table


@dataclass(frozen=True)
class Role:
    opening: str
    closing: str
    loss: bool
    after: tuple[str, ...]  # states it may follow


TEMPLATE = {
    "system": Role("<<SYS>> ", " <</SYS>>", False, ("start",)),
    "user": Role("[INST] ", " [/INST]", False, ("start", "system", "assistant")),
    "assistant": Role("[ANS] ", " </s>", True, ("user",)),
}
FINAL = ("assistant",)
OTHER = ("[ROLE {}] ", " [/ROLE]")
_ESCAPE = re.compile(r"[\\\[\]<]")
_UNESCAPE = re.compile(r"\\(.)", re.S)


def escape(text: str) -> str:
    return _ESCAPE.sub(lambda m: "\\" + m[0], text)


def unescape(text: str) -> str:
    return _UNESCAPE.sub(r"\1", text)


def marks(role: str, template=TEMPLATE) -> tuple[str, str, bool]:
    if role in template:
        r = template[role]
        return r.opening, r.closing, r.loss
    return OTHER[0].format(escape(role)), OTHER[1], False


def parse_turn(formatted: str, template=TEMPLATE) -> tuple[str, str]:
    """Role and text of one formatted turn."""
    for name, r in template.items():
        if formatted.startswith(r.opening):
            return name, unescape(formatted[len(r.opening) : len(formatted) - len(r.closing)])
    head, tail = OTHER[0].split("{}")
    end = re.compile(r"(?:\\.|[^\\\]])*", re.S).match(formatted, len(head)).end()
    return unescape(formatted[len(head) : end]), unescape(formatted[end + len(tail) : len(formatted) - len(OTHER[1])])


def step(state: str, role: str, template=TEMPLATE) -> str:
    """Next state; ``bad`` is final."""
    return role if state != "bad" and role in template and state in template[role].after else "bad"


SEGMENT_SCHEMA = "conv string, place long, segment int, text string, loss boolean, state string"


def segments(turns: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role",
             text_col: str = "text", template=TEMPLATE) -> DataFrame:
    """Segments in order within each partition; no conversation spans two partitions.

    place: number of the turn in its conversation; state: of the machine after the turn.
    """
    t = turns.select(
        turns[conv_col].cast("string").alias("conv"), turns[turn_col].alias("turn"),
        F.coalesce(turns[role_col].cast("string"), F.lit("")).alias("role"), F.coalesce(turns[text_col].cast("string"), F.lit("")).alias("text"))
    t = t.repartition("conv").sortWithinPartitions("conv", "turn", "role", "text")

    def run(batches):
        conv, place, state, fresh = None, 0, "start", True
        for b in batches:
            rows = []
            for c, role, text in zip(b["conv"], b["role"], b["text"]):
                if fresh or c != conv:
                    conv, place, state, fresh = c, 0, "start", False
                state = step(state, role, template)
                opening, closing, loss = marks(role, template)
                rows += [(c, place, 0, opening, False, state), (c, place, 1, escape(text), loss, state), (c, place, 2, closing, False, state)]
                place += 1
            yield pd.DataFrame(rows, columns=["conv", "place", "segment", "text", "loss", "state"])

    return t.mapInPandas(run, SEGMENT_SCHEMA)


def digests(parts: DataFrame, template=TEMPLATE) -> DataFrame:
    """Per conversation, read back from its segments: counts and SHA-256 of turns and of loss text."""

    def run(batches):
        conv, open_ = None, False
        done: list = []

        def finish():
            done.append((conv, n, turns.hexdigest(), loss_chars, loss.hexdigest(), chars, state in FINAL))

        for b in batches:
            for c, s, text, flag, st in zip(b["conv"], b["segment"], b["text"], b["loss"], b["state"]):
                if not open_ or c != conv:
                    if open_:
                        finish()
                    conv, open_, n, chars, loss_chars, buffer = c, True, 0, 0, 0, []
                    turns, loss = hashlib.sha256(), hashlib.sha256()
                state = st
                chars += len(text)
                buffer.append(text)
                if flag:
                    plain = unescape(text)
                    loss_chars += len(plain)
                    loss.update(plain.encode("utf-8"))
                if s == 2:
                    role, plain = parse_turn("".join(buffer), template)
                    turns.update(f"{role}\n{plain}\n".encode())
                    n, buffer = n + 1, []
            yield pd.DataFrame(done, columns=["conv", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "valid"])
            done = []
        if open_:
            finish()
            yield pd.DataFrame(done, columns=["conv", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "valid"])

    return parts.mapInPandas(run, "conv string, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, valid boolean")


PROBE = "</s>[INST] ok [/INST]"


def op7(spark, sf_dir: str) -> DataFrame:
    turns = read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.createDataFrame([(-7, 0, "user", PROBE), (-7, 1, "assistant", PROBE)], "conv_id long, turn long, role string, text string")
    d = digests(segments(turns.union(probe)))
    return d.select(F.col("conv").cast("long").alias("conv_id"), *d.columns[1:])


def oracle_sql() -> str:
    case = lambda f, other: "CASE role " + " ".join(f"WHEN '{k}' THEN {f(v)}" for k, v in TEMPLATE.items()) + f" ELSE {other} END"
    esc = lambda x: f"(2 * length({x}) - length(regexp_replace({x}, '[\\\\\\[\\]<]', '', 'g')))"
    head, tail = len(OTHER[0]) - 2, len(OTHER[1])
    frame = case(lambda r: len(r.opening) + len(r.closing), f"{head + tail} + {esc('role')}")
    state = "CASE role " + " ".join(f"WHEN '{k}' THEN p IN ({', '.join(repr(x) for x in v.after)})" for k, v in TEMPLATE.items()) + " ELSE false END"
    return f"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '{PROBE}' UNION ALL SELECT -7, 1, 'assistant', '{PROBE}'),
o AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS i FROM c),
p AS (SELECT *, coalesce(lag(role) OVER (PARTITION BY conv_id ORDER BY i), 'start') AS p FROM o),
f AS (SELECT *, {frame} + {esc('text')} AS chars, {state} AS fine FROM p)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY i)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY i) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(chars) AS BIGINT) AS formatted_chars, bool_and(fine) AND arg_max(role, i) = 'assistant' AS valid
FROM f GROUP BY conv_id"""
