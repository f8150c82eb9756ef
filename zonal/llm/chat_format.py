"""Chat formatting by schema fingerprints, in native expressions only.

A layout is recognised by the hash of its nested field paths: the paths that the record has,
out of the paths any declared layout knows, are sorted and hashed; the fingerprint picks a
declarative mapping from layout to canonical turns ``array<struct<role, text>>``. Tables are
fingerprinted once, from their schema; JSON records each on its own, through a variant.

Template: ``<|im_start|>role LF text <|im_end|> LF`` per turn. A control string inside a
text or role can't be told from a real one, so every ``<``, run of backslashes, ``|`` gets
one backslash more, and reading takes one away: a bijection that leaves other text alone.
A line feed in a role is written as a backslash and n, a backslash as two.
The loss mask is a list of (start, length) spans in code points over the formatted string;
it covers the texts of assistant turns, without role lines or end marks.

Defined results: null text or role counts as empty; turns with equal numbers are ordered by
role, then text, repeated rows stay; a null turn number comes first; a conversation without
turns doesn't appear; unknown fingerprints give null turns.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

TURN_TYPE = "array<struct<role:string,text:string>>"
START, END = "<|im_start|>", "<|im_end|>"

#: Declarative mappings. ``each`` names an array and its role and text fields; ``turns``
#: lists (role, path) pairs; ``rows`` are tables that hold one turn a row.
LAYOUTS: dict[str, dict] = {
    "turn_rows": {"paths": ["conv_id", "role", "text", "turn"], "rows": ("conv_id", "turn", "role", "text")},
    "messages": {"paths": ["messages.content", "messages.role"], "each": ("messages", "role", "content")},
    "from_value": {"paths": ["conversations.from", "conversations.value"], "each": ("conversations", "from", "value")},
    "prompt_response": {"paths": ["prompt", "response"], "turns": [("user", "prompt"), ("assistant", "response")]},
    "prompt_completion": {"paths": ["completion", "prompt"], "turns": [("user", "prompt"), ("assistant", "completion")]},
    "question_answer": {"paths": ["answer", "question"], "turns": [("user", "question"), ("assistant", "answer")]},
    "instruction": {"paths": ["instruction", "output"], "turns": [("user", "instruction"), ("assistant", "output")]},
    "instruction_input": {
        "paths": ["input", "instruction", "output"],
        "turns": [("user", "instruction+input"), ("assistant", "output")],
    },
    "system_prompt_response": {
        "paths": ["prompt", "response", "system"],
        "turns": [("system", "system"), ("user", "prompt"), ("assistant", "response")],
    },
}
#: Names of roles in the wild and their canonical forms.
ROLES = {"human": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant"}
KNOWN = sorted({p for x in LAYOUTS.values() for p in x["paths"]})


def fingerprint(paths: list[str]) -> str:
    """Hash of the known paths among ``paths``, whatever their order; others are ignored."""
    return hashlib.md5("\n".join(sorted(set(paths) & set(KNOWN))).encode()).hexdigest()


BY_FINGERPRINT = {fingerprint(x["paths"]): name for name, x in LAYOUTS.items()}


def field_paths(schema: T.StructType, prefix: str = "") -> list[str]:
    found = []
    for f in schema.fields:
        kind = f.dataType.elementType if isinstance(f.dataType, T.ArrayType) else f.dataType
        if isinstance(kind, T.StructType):
            found += field_paths(kind, f"{prefix}{f.name}.")
        else:
            found.append(prefix + f.name)
    return found


def layout_of(df: DataFrame) -> str | None:
    return BY_FINGERPRINT.get(fingerprint(field_paths(df.schema)))


def _role(col: Column) -> Column:
    col = F.coalesce(col.cast("string"), F.lit(""))
    out = col
    for wild, ours in ROLES.items():
        out = F.when(col == wild, F.lit(ours)).otherwise(out)
    return out


def _pair(role: Column, text: Column) -> Column:
    return F.struct(role.alias("role"), F.coalesce(text.cast("string"), F.lit("")).alias("text"))


def _joined(get, path: str) -> Column:
    return F.concat_ws("\n\n", *[F.nullif(get(p).cast("string"), F.lit("")) for p in path.split("+")])


def _turns(layout: dict, get, get_array) -> Column:
    if "each" in layout:
        array, role, text = layout["each"]
        return F.transform(get_array(array, role, text), lambda m: _pair(_role(m[role]), m[text]))
    pairs = [_pair(F.lit(role), _joined(get, path)) for role, path in layout["turns"]]
    return F.filter(F.array(*pairs), lambda t: (t["role"] != "system") | (t["text"] != ""))


def turns_from_table(df: DataFrame, key: str | None = None) -> DataFrame:
    """(key, turns) of a table whose schema matches a layout; ``key`` may name the id column."""
    name = layout_of(df)
    if name is None:
        raise ValueError("no declared layout has the field paths of this table")
    layout = LAYOUTS[name]
    if "rows" in layout:
        conv, turn, role, text = layout["rows"]
        rows = df.select(F.col(key or conv).alias("conv_id"), F.struct(F.col(turn).alias("turn"), F.coalesce(F.col(role), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text")).alias("t"))
        listed = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("ts"))
        return listed.select("conv_id", F.transform("ts", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))
    ident = F.col(key) if key else F.monotonically_increasing_id()
    turns = _turns(layout, lambda p: F.col(f"`{p}`"), lambda a, *_: F.col(f"`{a}`"))
    return df.select(ident.alias("conv_id"), turns.cast(TURN_TYPE).alias("turns"))


def turns_from_json(df: DataFrame, json_col: str, key: str) -> DataFrame:
    """(conv_id, fingerprint, layout, turns) of JSON records of mixed layouts."""
    v = df.select(F.col(key).alias("conv_id"), F.try_parse_json(F.col(json_col).cast("string")).alias("v"))

    def has(path: str) -> Column:
        top, _, leaf = path.partition(".")
        at = f"$.{top}[0].{leaf}" if leaf else f"$.{top}"
        return F.when(F.try_variant_get("v", at, "string").isNotNull(), F.lit(path))

    print_ = F.md5(F.concat_ws("\n", *[has(p) for p in KNOWN]))
    names = F.create_map(*[F.lit(x) for kv in BY_FINGERPRINT.items() for x in kv])
    v = v.withColumn("fingerprint", print_).withColumn("layout", F.try_element_at(names, F.col("fingerprint")))
    turns = F.lit(None).cast(TURN_TYPE)
    for name, layout in LAYOUTS.items():
        if "rows" not in layout:
            mapped = _turns(
                layout,
                lambda p: F.try_variant_get("v", f"$.{p}", "string"),
                lambda a, role, text: F.try_variant_get("v", f"$.{a}", f"array<struct<`{role}`:string,`{text}`:string>>"),
            )
            turns = F.when(F.col("layout") == name, mapped.cast(TURN_TYPE)).otherwise(turns)
    return v.select("conv_id", "fingerprint", "layout", turns.alias("turns"))


def escape(text: Column) -> Column:
    return F.regexp_replace(text, r"<(\\*)\|", r"<\\$1|")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"<\\(\\*)\|", r"<$1|")


def _escape_role(role: Column) -> Column:
    return escape(F.replace(F.replace(role, F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n")))


def _unescape_role(role: Column) -> Column:
    line_feeds = F.regexp_replace(unescape(role), r"(?<!\\)((?:\\\\)*)\\n", "$1\n")
    return F.replace(line_feeds, F.lit("\\\\"), F.lit("\\"))


def format_turns(df: DataFrame) -> DataFrame:
    """(conv_id, turns) to conv_id, formatted, loss_mask."""
    written = F.transform(
        "turns",
        lambda t: F.struct(
            F.concat(F.lit(START), _escape_role(t["role"]), F.lit("\n")).alias("head"),
            escape(t["text"]).alias("body"),
            (t["role"] == "assistant").alias("loss"),
        ),
    )
    df = df.select("conv_id", written.alias("w"))
    tail = END + "\n"
    at0 = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:bigint,length:bigint>>").alias("spans"))

    def step(acc: Column, w: Column) -> Column:
        begin = acc["at"] + F.length(w["head"])
        n = F.length(w["body"]).cast("long")
        span = F.array(F.struct(begin.alias("start"), n.alias("length")))
        return F.struct((begin + n + len(tail)).alias("at"), F.when(w["loss"], F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans"))

    return df.select(
        "conv_id",
        F.concat_ws("", F.transform("w", lambda w: F.concat(w["head"], w["body"], F.lit(tail)))).alias("formatted"),
        F.aggregate("w", at0, step)["spans"].alias("loss_mask"),
    )


def read_back(df: DataFrame) -> DataFrame:
    """(conv_id, formatted, loss_mask) to conv_id, turns, loss_text: the inverse of formatting."""
    parts = F.split("formatted", r"<\|im_start\|>")
    blocks = F.slice(parts, F.lit(2), F.size(parts) - 1)
    cut = len(END) + 1

    def turn(b: Column) -> Column:
        role = F.substring_index(b, "\n", 1)
        body = F.substring(b, F.length(role) + 2, F.length(b) - F.length(role) - 1 - cut)
        return F.struct(_unescape_role(role).alias("role"), unescape(body).alias("text"))

    masked = F.transform("loss_mask", lambda s: unescape(F.substring(F.col("formatted"), (s["start"] + 1).cast("int"), s["length"].cast("int"))))
    return df.select("conv_id", "formatted", F.transform(blocks, turn).alias("turns"), F.concat_ws("", masked).alias("loss_text"))
