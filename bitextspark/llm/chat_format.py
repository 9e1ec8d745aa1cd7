"""Chat formatting with schema fingerprints, in DataFrame functions only.

A record is a VARIANT. Its nested field paths, taken from its schema and cut
to those that any mapping knows, are hashed; the hash selects a declarative
mapping that turns the record's layout into canonical turns (role, text).
Turns are written to a template that marks them and escapes its own control
strings in roles and texts, so the text can be read back exactly; the loss
mask is a list of spans of the formatted text.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import combinations

import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The template's control strings.
OPEN, AFTER_ROLE, CLOSE = "### ", ": ", "</turn>\n"
TURNS = "array<struct<role:string,text:string>>"
LOSS_ROLE = "assistant"
# Names that other layouts give to roles.
ROLE_NAMES = {"human": "user", "prompter": "user", "customer": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant", "chatgpt": "assistant", "agent": "assistant"}


@dataclass(frozen=True)
class Listed:
    """A list of messages: where it is, and the names of a message's role and text; parts: the text is a list of objects that hold text."""

    name: str
    at: str
    role: str
    text: str
    rename: bool = False
    parts: str | None = None

    def layouts(self):
        inside = f"{self.at}[].{self.text}" + (f"[].{self.parts}" if self.parts else "")
        parents = [".".join(self.at.split(".")[: i + 1]) for i in range(self.at.count(".") + 1)]
        full = {*parents, f"{self.at}[].{self.role}", f"{self.at}[].{self.text}", inside}
        return [full] if self.parts else [full, set(parents)]

    def turns(self, record: Column) -> Column:
        text = f"array<struct<{self.parts}:string>>" if self.parts else "string"
        found = F.try_variant_get(record, f"$.{self.at}", f"array<struct<`{self.role}`:string,`{self.text}`:{text}>>")

        def turn(m: Column) -> Column:
            role, body = F.coalesce(m[self.role], F.lit("")), m[self.text]
            if self.rename:
                role = renamed(role)
            if self.parts:
                body = F.array_join(F.transform(body, lambda p: F.coalesce(p[self.parts], F.lit(""))), "")
            return F.struct(role.alias("role"), F.coalesce(body, F.lit("")).alias("text"))

        return F.transform(F.coalesce(found, F.array().cast(found_type(self, text))), turn)


def found_type(m: Listed, text: str) -> str:
    return f"array<struct<`{m.role}`:string,`{m.text}`:{text}>>"


@dataclass(frozen=True)
class Fields:
    """One field a turn: (role, fields whose non-empty texts make the turn, an empty line between); optional fields may be missing."""

    name: str
    turn_fields: tuple[tuple[str, tuple[str, ...]], ...]
    optional: tuple[str, ...] = field(default=())

    def layouts(self):
        def closed(paths):
            return {".".join(p.split(".")[: i + 1]) for p in paths for i in range(p.count(".") + 1)}

        every = {p for _, paths in self.turn_fields for p in paths}
        return [closed(every - set(gone)) for n in range(len(self.optional) + 1) for gone in combinations(self.optional, n)]

    def turns(self, record: Column) -> Column:
        made = []
        for role, paths in self.turn_fields:
            texts = [F.try_variant_get(record, f"$.{p}", "string") for p in paths]
            text = F.array_join(F.filter(F.array(*texts), lambda t: t.isNotNull() & (t != "")), "\n\n")
            turn = F.struct(F.lit(role).alias("role"), text.alias("text"))
            made.append(F.when(F.coalesce(*texts).isNotNull(), turn) if set(paths) <= set(self.optional) else turn)
        return F.array_compact(F.array(*made))


#: Mappings by precedence; of two with one fingerprint the first holds.
MAPPINGS: tuple[Listed | Fields, ...] = (
    Listed("messages", "messages", "role", "content"),
    Listed("messages_text", "messages", "role", "text"),
    Listed("messages_parts", "messages", "role", "content", parts="text"),
    Listed("from_value", "conversations", "from", "value", rename=True),
    Listed("conversation", "conversation", "role", "content"),
    Listed("speakers", "dialog.turns", "speaker", "utterance", rename=True),
    Fields("instruction", (("system", ("system",)), ("user", ("instruction", "input")), ("assistant", ("output",))), ("system", "input")),
    Fields("instruction_response", (("system", ("system",)), ("user", ("instruction", "context")), ("assistant", ("response",))), ("system", "context")),
    Fields("prompt_response", (("system", ("system",)), ("user", ("prompt",)), ("assistant", ("response",))), ("system",)),
    Fields("prompt_completion", (("system", ("system",)), ("user", ("prompt",)), ("assistant", ("completion",))), ("system",)),
    Fields("preference", (("user", ("prompt",)), ("assistant", ("chosen",)))),
    Fields("question", (("user", ("context", "question")), ("assistant", ("answer",))), ("context",)),
    Fields("nested_prompt", (("user", ("data.prompt",)), ("assistant", ("data.response",)))),
)


def digest(paths) -> int:
    """Fingerprint of a set of paths: XXH64 of them in order, as Spark's xxhash64 gives it."""
    found = xxhash.xxh64_intdigest("\n".join(sorted(paths)).encode(), 42)
    return found - (1 << 64) if found >> 63 else found


def registry(mappings=MAPPINGS) -> tuple[list[str], dict[int, int]]:
    """(all paths that a mapping knows, fingerprint -> number of its mapping)."""
    known, by = set(), {}
    for i, m in enumerate(mappings):
        for paths in m.layouts():
            known |= paths
            by.setdefault(digest(paths), i)
    return sorted(known), by


def renamed(role: Column) -> Column:
    names = F.create_map(*(F.lit(x) for pair in ROLE_NAMES.items() for x in pair))
    return F.coalesce(F.try_element_at(names, F.lower(role)), role)


def field_paths(record: Column) -> Column:
    """Nested field paths of a VARIANT as a sorted array: a.b for objects, a[].b through arrays; scalar types are left out.

    The schema text is folded token by token: a name waits until its value
    shows whether it is an object, an array or a scalar.
    """
    tokens = F.regexp_extract_all(F.schema_of_variant(record), F.lit(r"OBJECT<|ARRAY<|>|(?:`(?:[^`]|``)*`|[^<>,:\s`]+): "), F.lit(0))
    start = F.struct(F.array(F.lit("")).alias("stack"), F.lit("").alias("at"), F.array().cast("array<string>").alias("paths"))

    def step(acc: Column, token: Column) -> Column:
        top = F.element_at(acc["stack"], -1)
        name = F.regexp_replace(F.substring(token, F.lit(1), F.length(token) - 2), "^`(.*)`$", "$1")
        full = F.concat(top, F.when(top == "", "").otherwise("."), name)
        push = lambda x: F.struct(F.concat(acc["stack"], F.array(x)).alias("stack"), acc["at"].alias("at"), acc["paths"].alias("paths"))
        return (
            F.when(token == "OBJECT<", push(acc["at"]))
            .when(token == "ARRAY<", F.struct(F.concat(acc["stack"], F.array(top)).alias("stack"), F.concat(acc["at"], F.lit("[]")).alias("at"), acc["paths"].alias("paths")))
            .when(token == ">", F.struct(F.slice(acc["stack"], F.lit(1), F.greatest(F.size(acc["stack"]) - 1, F.lit(1))).alias("stack"), top.alias("at"), acc["paths"].alias("paths")))
            .otherwise(F.struct(acc["stack"].alias("stack"), full.alias("at"), F.concat(acc["paths"], F.array(full)).alias("paths")))
        )

    return F.array_sort(F.array_distinct(F.aggregate(tokens, start, step, lambda acc: acc["paths"])))


def fingerprint(record: Column, known: list[str]) -> Column:
    return F.xxhash64(F.array_join(F.array_intersect(field_paths(record), F.array(*map(F.lit, known))), "\n"))


def escape(text: Column) -> Column:
    """No control string is left: backslashes are doubled, ## and </turn> are broken by one. Roles lose their colons, too (escape_role)."""
    out = F.replace(text, F.lit("\\"), F.lit("\\\\"))
    return F.replace(F.replace(out, F.lit("##"), F.lit("#\\#")), F.lit("</turn>"), F.lit("<\\/turn>"))


def escape_role(role: Column) -> Column:
    return F.replace(escape(role), F.lit(":"), F.lit("\\:"))


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def canonical(records: DataFrame, record_col: str = "record", mappings=MAPPINGS) -> DataFrame:
    """records with layout (the mapping's name, null: none fits), fingerprint and turns behind their columns.

    Text records are parsed as JSON; what isn't JSON, a null record and a
    layout without a mapping have null turns and stay in the table.
    """
    known, by = registry(mappings)
    record = F.col(record_col) if records.schema[record_col].dataType.typeName() == "variant" else F.try_parse_json(F.col(record_col))
    out = records.withColumn("__record", record).withColumn("fingerprint", fingerprint(F.col("__record"), known))
    of: dict[int, list[int]] = {}
    for h, i in by.items():
        of.setdefault(i, []).append(h)
    layout, turns = F.lit(None).cast("string"), F.lit(None).cast(TURNS)
    for i, hashes in of.items():
        fits = F.col("fingerprint").isin(hashes)
        layout = F.when(fits, F.lit(mappings[i].name)).otherwise(layout)
        turns = F.when(fits, mappings[i].turns(F.col("__record")).cast(TURNS)).otherwise(turns)
    return out.withColumns({"layout": layout, "turns": turns}).drop("__record")


def formatted(chats: DataFrame, turns_col: str = "turns") -> DataFrame:
    """chats with formatted (text) and loss_spans (first code point from 0, code points) behind their columns; null turns give nulls."""
    parts = F.transform(F.col(turns_col), lambda t: F.struct(
        F.concat(F.lit(OPEN), escape_role(F.coalesce(t["role"], F.lit(""))), F.lit(AFTER_ROLE)).alias("head"),
        escape(F.coalesce(t["text"], F.lit(""))).alias("body"), (F.coalesce(t["role"], F.lit("")) == LOSS_ROLE).alias("loss"),
    ))
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:bigint,length:bigint>>").alias("spans"))

    def step(acc: Column, p: Column) -> Column:
        first, size = acc["at"] + F.length(p["head"]), F.length(p["body"]).cast("long")
        span = F.array(F.struct(first.alias("start"), size.alias("length")))
        return F.struct((first + size + len(CLOSE)).alias("at"), F.when(p["loss"], F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans"))

    whole = F.array_join(F.transform(F.col("__parts"), lambda p: F.concat(p["head"], p["body"], F.lit(CLOSE))), "")
    return chats.withColumn("__parts", parts).withColumns({"formatted": whole, "loss_spans": F.aggregate("__parts", start, step, lambda acc: acc["spans"])}).drop("__parts")


def read_turns(text: Column) -> Column:
    """The turns of a formatted text."""
    pieces = F.split(text, "</turn>\n", -1)
    # the role ends at the first colon that isn't escaped
    role = r"(?s)^### ((?:[^\\:]++|\\.)*+): "
    return F.transform(F.slice(pieces, 1, F.greatest(F.size(pieces) - 1, F.lit(0))), lambda p: F.struct(unescape(F.regexp_extract(p, role, 1)).alias("role"), unescape(F.regexp_replace(p, role, "")).alias("text")))


def read_loss(text: Column, spans: Column) -> Column:
    """The unescaped texts under the loss mask, in order."""
    return F.transform(spans, lambda s: unescape(F.substring(text, s["start"].cast("int") + 1, s["length"].cast("int"))))


def gather(rows: DataFrame, id_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """(id, record): the rows of each conversation by turn, as one record in the messages_text layout.

    A conversation is formatted as a whole, so its rows meet in one place;
    ties of turn go by role and text. Null texts are empty, a null role too.
    """
    row = F.struct(F.col(turn_col).alias("n"), F.coalesce(role_col, F.lit("")).alias("role"), F.coalesce(text_col, F.lit("")).alias("text"))
    grouped = rows.groupBy(F.col(id_col)).agg(F.array_sort(F.collect_list(row)).alias("x"))
    messages = F.transform("x", lambda m: F.struct(m["role"].alias("role"), m["text"].alias("text")))
    return grouped.select(id_col, F.to_variant_object(F.struct(messages.alias("messages"))).alias("record"))


def format_digests(chats: DataFrame, id_col: str = "conv_id") -> DataFrame:
    """(id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars) read back from formatted and loss_spans."""
    read = chats.select(id_col, "formatted", read_turns(F.col("formatted")).alias("__turns"), read_loss(F.col("formatted"), F.col("loss_spans")).alias("__loss"))
    flat = F.array_join(F.transform("__turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join("__loss", "")
    return read.select(id_col, F.size("__turns").cast("long").alias("n_turns"), F.sha2(flat, 256).alias("turns_sha256"), F.length(loss).cast("long").alias("loss_chars"), F.sha2(loss, 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"))
