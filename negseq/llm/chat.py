"""Chat formatting by schema fingerprints, in DataFrame functions only.

The fingerprint of a layout is a hash of its nested field paths with their types. A
registry maps fingerprints to declarative mappings, which say where the turns are and what
their role and text are; a table of an unknown layout is refused by name. Canonical turns
are an array of (role, text), which a template turns into one string:

    <|im_start|>role\\ntext<|im_end|>\\n

In roles and texts a backslash becomes two and ``<|`` becomes ``<\\|``; no control
string can then occur in a text, and undoing both is exact. A role's line breaks are
written as ``\\n`` in the same manner. Reading back splits at the control strings only.

Defined results: null text is empty, a null role is ``user``; turns of equal number
come in the order of role and text; a null conversation id is a conversation of its own;
a conversation of no turns cannot occur in rows and is an empty string in arrays.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

START, END = "<|im_start|>", "<|im_end|>"
TURNS = "array<struct<role: string, text: string>>"


def field_paths(schema: T.StructType, at: str = "") -> list[str]:
    """Nested paths with the type of each leaf; [] stands for the elements of an array."""
    out = []
    for f in schema.fields:
        path, kind = f"{at}{f.name}", f.dataType
        while isinstance(kind, T.ArrayType):
            path, kind = f"{path}[]", kind.elementType
        out += field_paths(kind, f"{path}.") if isinstance(kind, T.StructType) else [f"{path}:{kind.simpleString()}"]
    return sorted(out)


def fingerprint(schema: T.StructType, ignore: tuple[str, ...] = ()) -> str:
    """A hash of the paths that matter to the layout, whatever their order; columns in ignore do not."""
    import hashlib

    kept = T.StructType([f for f in schema.fields if f.name not in ignore])
    return hashlib.sha256("\n".join(field_paths(kept)).encode()).hexdigest()[:16]


@dataclass(frozen=True)
class Mapping:
    """Where a layout keeps its turns. pairs: (role, SQL expression of the text, whether a blank one is left out) for flat layouts; messages: (array, role field, text field); rows: (conversation, order, role, text) for one row per turn."""

    name: str
    schema: str
    pairs: tuple[tuple[str, str, bool], ...] = ()
    messages: tuple[str, str, str] | None = None
    rows: tuple[str, str, str, str] | None = None
    roles: tuple[tuple[str, str], ...] = ()


#: Layouts known from the start; registry() accepts more.
KNOWN = (
    Mapping("prompt and completion", "prompt string, completion string", (("user", "prompt", False), ("assistant", "completion", False))),
    Mapping("prompt and response", "prompt string, response string", (("user", "prompt", False), ("assistant", "response", False))),
    Mapping("question and answer", "question string, answer string", (("user", "question", False), ("assistant", "answer", False))),
    Mapping("system prompt and completion", "system string, prompt string, completion string", (("system", "system", True), ("user", "prompt", False), ("assistant", "completion", False))),
    Mapping("instruction", "instruction string, output string", (("user", "instruction", False), ("assistant", "output", False))),
    Mapping("instruction with input", "instruction string, input string, output string", (("user", "concat_ws('\\n\\n', instruction, nullif(input, ''))", False), ("assistant", "output", False))),
    Mapping("messages", "messages array<struct<role: string, content: string>>", messages=("messages", "role", "content")),
    Mapping("conversations", "conversations array<struct<from: string, value: string>>", messages=("conversations", "from", "value"), roles=(("human", "user"), ("gpt", "assistant"), ("bot", "assistant"))),
    Mapping("turn rows", "conv_id bigint, turn bigint, role string, text string", rows=("conv_id", "turn", "role", "text")),
)


def registry(*more: Mapping) -> dict[str, Mapping]:
    out = {}
    for m in (*KNOWN, *more):
        out[fingerprint(T._parse_datatype_string(m.schema) if isinstance(m.schema, str) else m.schema)] = m
    return out


def _role(column: Column, roles: tuple[tuple[str, str], ...]) -> Column:
    out = column
    for a, b in roles:
        out = F.when(column == a, F.lit(b)).otherwise(out)
    return F.coalesce(out, F.lit("user"))


def canonical(df: DataFrame, known: dict[str, Mapping] | None = None, id_col: str | None = None, ignore: tuple[str, ...] = ()) -> DataFrame:
    """conv_id, turns. id_col: the column that identifies a row of an array or flat layout; it and the columns in ignore are no part of the fingerprint."""
    known = known or registry()
    left_out = (*ignore, *([id_col] if id_col else []))
    mapping = known.get(fingerprint(df.schema, left_out))
    if mapping is None:
        raise ValueError("no mapping for the layout " + ", ".join(field_paths(T.StructType([f for f in df.schema.fields if f.name not in left_out]))))
    if mapping.rows:
        conv, order, role, text = map(F.col, mapping.rows)
        turn = F.struct(order.alias("at"), _role(role, mapping.roles).alias("role"), F.coalesce(text, F.lit("")).alias("text"))
        grouped = df.groupBy(conv.alias("conv_id")).agg(F.sort_array(F.collect_list(turn)).alias("turns"))
        return grouped.select("conv_id", F.transform("turns", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))
    ids = F.col(id_col).alias("conv_id") if id_col else F.lit(None).cast("long").alias("conv_id")
    if mapping.messages:
        array, role, text = mapping.messages
        turns = F.transform(F.coalesce(F.col(array), F.array()), lambda t: F.struct(_role(t[role], mapping.roles).alias("role"), F.coalesce(t[text], F.lit("")).alias("text")))
    else:
        each = [F.when(F.lit(optional) & (F.coalesce(F.expr(sql), F.lit("")) == ""), F.lit(None)).otherwise(F.struct(F.lit(role).alias("role"), F.coalesce(F.expr(sql), F.lit("")).alias("text"))) for role, sql, optional in mapping.pairs]
        turns = F.filter(F.array(*each), lambda t: t.isNotNull())
    return df.select(ids, turns.cast(TURNS).alias("turns"))


def escape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescape(text: Column) -> Column:
    """One pass from the left: a backslash gives way to the backslash or bar after it."""
    return F.regexp_replace(text, r"\\([\\|])", "$1")


def formatted(turns: Column | str) -> Column:
    """One string of all turns."""
    line = lambda role: F.replace(escape(role), F.lit("\n"), F.lit("\\n"))
    parts = F.transform(turns, lambda t: F.concat(F.lit(START), line(t["role"]), F.lit("\n"), escape(t["text"]), F.lit(END + "\n")))
    return F.array_join(parts, "")


def parsed(text: Column | str) -> Column:
    """Turns read back from the output, with start: the place (from 1) of each text in it, and raw: the text as written."""
    text = F.col(text) if isinstance(text, str) else text
    pieces = F.filter(F.split(text, r"<\|im_start\|>"), lambda x: x != "")
    body = lambda x: F.left(x, F.length(x) - len(END) - 1)
    rows = F.transform(pieces, lambda x: F.struct(F.length(x).alias("size"), F.substring_index(body(x), "\n", 1).alias("head"), body(x).alias("body")))
    rows = F.transform(rows, lambda r: F.struct(r["size"].alias("size"), r["head"].alias("head"), F.substring(r["body"], F.length(r["head"]) + 2, F.length(r["body"])).alias("raw")))
    return rows


def with_output(conversations: DataFrame) -> DataFrame:
    """conv_id, turns -> conv_id, formatted, loss: the spans (first character from 0, length) of assistant texts in the output."""
    out = conversations.select("conv_id", formatted("turns").alias("formatted"))
    out = out.withColumn("_rows", parsed("formatted"))
    spans = F.aggregate(
        "_rows",
        F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<first: int, size: int>>").alias("spans")),
        lambda s, r: F.struct(
            (s["at"] + len(START) + r["size"]).alias("at"),
            F.when(r["head"] == "assistant", F.concat(s["spans"], F.array(F.struct((s["at"] + len(START) + F.length(r["head"]) + 1).alias("first"), F.length(r["raw"]).alias("size"))))).otherwise(s["spans"]).alias("spans"),
        ),
        lambda s: s["spans"],
    )
    return out.select("conv_id", "formatted", spans.alias("loss"))


def read_back(output: DataFrame) -> DataFrame:
    """conv_id, turns, loss_text from the formatted string and its loss mask alone."""
    rows = output.select("conv_id", "formatted", "loss", parsed("formatted").alias("_rows"))
    turns = F.transform("_rows", lambda r: F.struct(unescape(_unline(r["head"])).alias("role"), unescape(r["raw"]).alias("text")))
    loss = F.array_join(F.transform("loss", lambda s: unescape(F.substring(F.col("formatted"), s["first"] + 1, s["size"]))), "")
    return rows.select("conv_id", turns.alias("turns"), loss.alias("loss_text"), "formatted")


def _unline(head: Column) -> Column:
    """Line breaks of a role: ``\\n`` stands for one unless its backslash is the second of a pair."""
    return F.regexp_replace(head, r"(?<!\\)((?:\\\\)*)\\n", "$1\n")
