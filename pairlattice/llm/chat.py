"""Chat formatting with DataFrame functions only.

A declarative template gives the markers, the control strings to escape and the roles under the
loss; a finite-state machine over roles checks the order of the turns.

Defined results: turns go by (turn, role, text), nulls first, repeated rows are turns of their own;
a null text or role is empty; a null conversation id is a conversation; an empty table gives no
rows; further columns are ignored.  A conversation is one row of the result, so its size is bounded
by what one string holds.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ESCAPE = "\\"


@dataclass(frozen=True)
class ChatTemplate:
    """``open`` + role + ``\\n`` + text + ``close`` for each turn; ``controls`` never appear unescaped inside a text."""

    open: str = "<|im_start|>"
    close: str = "<|im_end|>\n"
    controls: tuple[str, ...] = ("<|im_start|>", "<|im_end|>", "<s>", "</s>", "[INST]", "[/INST]")
    loss_roles: tuple[str, ...] = ("assistant",)
    start: str = "start"
    accepting: tuple[str, ...] = ("assistant",)
    #: (state, role) -> state; any other pair is an error.
    moves: dict = field(default_factory=lambda: {("start", "system"): "system", ("start", "user"): "user", ("system", "user"): "user", ("user", "assistant"): "assistant", ("assistant", "user"): "user"})

    def __post_init__(self):
        if any(len(c) < 2 or ESCAPE in c for c in self.controls) or not any(c in self.open for c in self.controls) or not any(c in self.close for c in self.controls):
            raise ValueError("controls need two characters, no escape character, and must cover the markers")


def escape(text: Column, template: ChatTemplate) -> Column:
    """Double the escape character, then put one after the first character of every control string."""
    out = F.replace(text, F.lit(ESCAPE), F.lit(ESCAPE * 2))
    for c in template.controls:
        out = F.replace(out, F.lit(c), F.lit(c[0] + ESCAPE + c[1:]))
    return out


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def conversations(rows: DataFrame) -> DataFrame:
    """(conv_id, turns): the turns of each conversation in order."""
    turn = F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.groupBy("conv_id").agg(F.sort_array(F.collect_list(turn)).alias("turns"))


def first_error(turns: Column, template: ChatTemplate) -> Column:
    """Index of the first turn that the machine refuses, the number of turns if it ends in a state that is not accepting, else -1."""
    moves = F.create_map(*[F.lit(x) for (state, role), to in template.moves.items() for x in (f"{state}\n{role}", to)])
    begin = F.struct(F.lit(template.start).alias("state"), F.lit(0).alias("at"), F.lit(-1).alias("bad"))

    def step(acc: Column, t: Column) -> Column:
        to = F.try_element_at(moves, F.concat(acc["state"], F.lit("\n"), t["role"]))
        return F.struct(F.coalesce(to, F.lit("")).alias("state"), (acc["at"] + 1).alias("at"), F.when((acc["bad"] < 0) & to.isNull(), acc["at"]).otherwise(acc["bad"]).alias("bad"))

    return F.aggregate(turns, begin, step, lambda acc: F.when((acc["bad"] < 0) & ~acc["state"].isin(*template.accepting), acc["at"]).otherwise(acc["bad"]))


def format_chats(rows: DataFrame, template: ChatTemplate | None = None) -> DataFrame:
    """(conv_id, turns, valid, first_error, segments, formatted).

    ``segments`` holds (text, loss) pieces whose texts, one after another, are ``formatted``.
    """
    template = template or ChatTemplate()
    seg = lambda text, loss: F.struct(text.alias("text"), loss.alias("loss"))
    role = lambda t: F.replace(escape(t["role"], template), F.lit("\n"), F.lit(ESCAPE + "\n"))
    pieces = F.flatten(F.transform("turns", lambda t: F.array(
        seg(F.concat(F.lit(template.open), role(t), F.lit("\n")), F.lit(False)),
        seg(escape(t["text"], template), t["role"].isin(*template.loss_roles)),
        seg(F.lit(template.close), F.lit(False)),
    )))
    return (
        conversations(rows)
        .withColumn("first_error", first_error(F.col("turns"), template))
        .withColumn("valid", F.col("first_error") < 0)
        .withColumn("segments", pieces)
        .withColumn("formatted", F.array_join(F.transform("segments", lambda s: s["text"]), ""))
    )


def read_back(formatted: Column, template: ChatTemplate | None = None) -> Column:
    """Array of (role, text) parsed from a formatted conversation."""
    template = template or ChatTemplate()
    head = r"(?s)^((?:[^\\\n]|\\.)*+)\n(.*)$"
    quote = "".join("\\" + c if not c.isalnum() and c not in "\n" else c for c in template.close)
    parts = F.filter(F.split(formatted, quote, -1), lambda s: s != "")
    body = lambda s: F.substring(s, len(template.open) + 1, 2147483647)
    return F.transform(parts, lambda s: F.struct(unescape(F.regexp_extract(body(s), head, 1)).alias("role"), unescape(F.regexp_extract(body(s), head, 2)).alias("text")))


def digests(chats: DataFrame, template: ChatTemplate | None = None) -> DataFrame:
    """Digest columns, read back from ``formatted`` and, for the loss, from ``segments``."""
    lines = F.array_join(F.transform("back", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join(F.transform(F.filter("segments", lambda s: s["loss"]), lambda s: unescape(s["text"])), "")
    return (
        chats.withColumn("back", read_back(F.col("formatted"), template))
        .withColumn("loss_text", loss)
        .select(
            "conv_id", F.size("back").cast("long").alias("n_turns"), F.sha2(F.encode(lines, "UTF-8"), 256).alias("turns_sha256"),
            F.length("loss_text").cast("long").alias("loss_chars"), F.sha2(F.encode("loss_text", "UTF-8"), 256).alias("loss_sha256"),
            F.length("formatted").cast("long").alias("formatted_chars"), "valid",
        )
    )


def oracle(template: ChatTemplate | None = None) -> str:
    """The digests in DuckDB SQL, from the turns themselves and the lengths that the template adds."""
    template = template or ChatTemplate()
    quote = lambda s: "'" + s.replace("'", "''") + "'" if "\n" not in s else " || chr(10) || ".join("'" + x + "'" for x in s.split("\n"))

    def esc(x: str) -> str:
        x = f"replace({x}, '\\', '\\\\')"
        for c in template.controls:
            x = f"replace({x}, {quote(c)}, {quote(c[0] + ESCAPE + c[1:])})"
        return x

    fixed = len(template.open) + 1 + len(template.close)
    roles = ", ".join(quote(r) for r in template.loss_roles)
    return f"""
WITH r AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]'
  UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), o AS (
  SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS pos,
         lag(role) OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS before,
         count(*) OVER (PARTITION BY conv_id) AS n
  FROM r
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY pos)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (WHERE role IN ({roles})), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY pos) FILTER (WHERE role IN ({roles})), '')) AS loss_sha256,
  CAST(sum({fixed} + length(replace({esc('role')}, chr(10), '\\' || chr(10))) + length({esc('text')})) AS BIGINT) AS formatted_chars,
  bool_and(CASE role WHEN 'system' THEN before IS NULL WHEN 'user' THEN coalesce(before, 'system') IN ('system', 'assistant')
           WHEN 'assistant' THEN coalesce(before, '') = 'user' ELSE false END AND (pos < n OR role = 'assistant')) AS valid
FROM o GROUP BY conv_id
"""
