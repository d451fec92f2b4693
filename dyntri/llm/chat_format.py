"""Chat formatting by schema fingerprints, in DataFrame functions only.

Records of unlike layouts are told apart by a fingerprint: a hash of their nested field paths. Each known fingerprint
selects a declarative mapping, which turns the record into canonical turns (role, text). A template then renders turns
with control strings around them and escapes control strings inside texts, so that the rendering can be read back.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

TURNS = "array<struct<role:string,text:string>>"

# ------------------------------------------------------------------ layouts


@dataclass(frozen=True)
class Layout:
    """How records with exactly these field paths become turns.

    paths: field paths, "[]" for list elements, scalar leaves only. turns: for a list layout (list path, role field,
    text field); otherwise ((role, path), ...) of single fields, in turn order; a null or missing field gives no turn;
    ("rows", key) for tables with a row per turn.
    roles: names to canonical ones.
    """

    name: str
    paths: tuple[str, ...]
    turns: tuple
    roles: tuple[tuple[str, str], ...] = (("human", "user"), ("gpt", "assistant"), ("bot", "assistant"), ("model", "assistant"))


LAYOUTS = (
    Layout("messages", ("messages[].content", "messages[].role"), ("messages", "role", "content")),
    Layout("conversations", ("conversations[].from", "conversations[].value"), ("conversations", "from", "value")),
    Layout("instruction", ("instruction", "output"), (("user", "instruction"), ("assistant", "output"))),
    Layout("instruction_input", ("input", "instruction", "output"), (("user", ("instruction", "input")), ("assistant", "output"))),
    Layout("system_instruction", ("instruction", "output", "system"), (("system", "system"), ("user", "instruction"), ("assistant", "output"))),
    Layout("prompt_completion", ("completion", "prompt"), (("user", "prompt"), ("assistant", "completion"))),
    Layout("prompt_response", ("prompt", "response"), (("user", "prompt"), ("assistant", "response"))),
    Layout("question_answer", ("answer", "question"), (("user", "question"), ("assistant", "answer"))),
    Layout("turn_rows", ("conv_id", "role", "text", "turn"), ("rows", "conv_id")),
)


def fingerprint(paths: tuple[str, ...]) -> str:
    import hashlib

    return hashlib.sha256("\n".join(sorted(paths)).encode()).hexdigest()


def schema_paths(schema: T.DataType, at: str = "") -> tuple[str, ...]:
    """Field paths of a Spark schema, down to scalars."""
    if isinstance(schema, T.StructType):
        return tuple(p for f in schema.fields for p in schema_paths(f.dataType, f"{at}.{f.name}" if at else f.name))
    if isinstance(schema, T.ArrayType):
        return schema_paths(schema.elementType, f"{at}[]")
    return (at,)


def record_fingerprint(json: Column) -> Column:
    """The fingerprint of a JSON record, per row: its variant schema as sorted paths, hashed.

    ``schema_of_variant`` writes OBJECT<a: ARRAY<OBJECT<b: STRING>>, c: BIGINT>; names and nesting stay, scalar types
    go. Layouts of up to two levels are told apart, which all known ones are; others get a fingerprint that none has.
    """
    kind = F.schema_of_variant(F.try_parse_json(json))
    inner = F.regexp_extract_all(kind, F.lit(r"(\w+): (?:ARRAY<OBJECT<([^<>]*)>>|ARRAY<[A-Z]+>|[A-Z]+(?:\(\d+,\s*\d+\))?)(?=[,>])"), F.lit(0))

    def paths(field: Column) -> Column:
        name = F.regexp_extract(field, r"^(\w+):", 1)
        nested = F.regexp_extract(field, r"ARRAY<OBJECT<([^<>]*)>>", 1)
        leaves = F.transform(F.split(nested, ", "), lambda x: F.concat(name, F.lit("[]."), F.regexp_extract(x, r"^(\w+):", 1)))
        return F.when(nested != "", leaves).when(field.contains(": ARRAY<"), F.array(F.concat(name, F.lit("[]")))).otherwise(F.array(name))

    return F.sha2(F.array_join(F.array_sort(F.flatten(F.transform(inner, paths))), "\n"), 256)


def _canonical(role: Column, layout: Layout) -> Column:
    names = F.create_map(*[F.lit(x) for pair in layout.roles for x in pair])
    low = F.lower(role)
    return F.coalesce(names[low], low)


def _turns(layout: Layout, get) -> Column:
    """Turns of a record; get(path) is a field, get(list path, (role, text)) a list of structs with these names."""
    if isinstance(layout.turns[0], str):
        path, role, text = layout.turns
        items = F.coalesce(get(path, (role, text)), F.array().cast(f"array<struct<{role}:string,{text}:string>>"))
        return F.transform(items, lambda x: F.struct(_canonical(x[role], layout).alias("role"), F.coalesce(x[text], F.lit("")).alias("text")))
    made = []
    for role, fields in layout.turns:
        fields = (fields,) if isinstance(fields, str) else fields
        parts = F.filter(F.array(*[get(f) for f in fields]), lambda x: x.isNotNull() & (x != ""))
        text = F.when(F.coalesce(*[get(f) for f in fields]).isNotNull(), F.array_join(parts, "\n\n"))
        made.append(F.struct(F.lit(role).alias("role"), text.alias("text")))
    return F.filter(F.array(*made), lambda t: t["text"].isNotNull())


def turns_of_json(records: DataFrame, column: str = "record", layouts: tuple[Layout, ...] = LAYOUTS) -> DataFrame:
    """records with ``fingerprint``, ``layout`` and ``turns`` from a column of JSON records of mixed layouts.

    A record of no known layout (or no JSON, or null) has a null layout and null turns. Columns with these names give way.
    """
    mark = F.col("fingerprint")
    name, turns = F.lit(None).cast("string"), F.lit(None).cast(TURNS)
    for layout in layouts:
        if layout.turns[0] == "rows":
            continue

        def get(path: str, inner: tuple[str, str] | None = None) -> Column:
            if inner:
                kind = f"{path} array<struct<{', '.join(f'`{x}`: string' for x in inner)}>>"
                return F.from_json(F.col(column), kind)[path]
            return F.get_json_object(F.col(column), f"$.{path}")

        own = mark == fingerprint(layout.paths)
        name, turns = F.when(own, layout.name).otherwise(name), F.when(own, _turns(layout, get)).otherwise(turns)
    kept = [c for c in records.columns if c not in ("fingerprint", "layout", "turns")]
    return records.select(*kept, record_fingerprint(F.col(column)).alias("fingerprint")).select(*kept, "fingerprint", name.alias("layout"), turns.cast(TURNS).alias("turns"))


def turns_of_table(df: DataFrame, layouts: tuple[Layout, ...] = LAYOUTS, keep: tuple[str, ...] = ()) -> DataFrame:
    """``keep`` and ``turns`` of a table whose schema, less ``keep``, has a known fingerprint; ValueError otherwise.

    A table with a row per turn gives its key and ``turns``.
    """
    mark = fingerprint(schema_paths(T.StructType([f for f in df.schema.fields if f.name not in keep])))
    for layout in layouts:
        if fingerprint(layout.paths) == mark:
            if layout.turns[0] == "rows":
                return turns_of_rows(df, layout.turns[1])
            return df.select(*keep, _turns(layout, lambda path, inner=None: F.col(path)).cast(TURNS).alias("turns"))
    raise ValueError(f"no layout for fingerprint {mark}")


def turns_of_rows(rows: DataFrame, key: str = "conv_id") -> DataFrame:
    """(key, turns) from a table with a row per turn: key, turn, role, text.

    Turns go by turn number (nulls first), then role and text; a null text is empty, a null role too. A conversation
    becomes one value, so its rows meet in one task by nature; no other grouping is made.
    """
    item = F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    grouped = rows.groupBy(key).agg(F.array_sort(F.collect_list(item)).alias("turns"))
    return grouped.select(key, F.transform("turns", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))


# ------------------------------------------------------------------ templates


@dataclass(frozen=True)
class Template:
    """marks: (role, opening, closing); other: opening, middle and closing of any further role, the role in between.

    Control strings are found in texts by ``controls``, a pattern of two groups: a first character and the rest. A
    backslash goes between them, and one more where some are there already, so taking one away restores the text.
    Each mark begins or ends with a space where a text joins it, and control strings have none: none can arise across
    the seam.
    """

    marks: tuple[tuple[str, str, str], ...]
    other: tuple[str, str, str]
    first: str
    rest: str
    turn_ends: str = ""

    def escaped(self, text: Column) -> Column:
        return F.regexp_replace(text, rf"({self.first})(\\*)({self.rest})", r"$1\\$2$3")

    def unescaped(self, text: Column) -> Column:
        return F.regexp_replace(text, rf"({self.first})\\(\\*)({self.rest})", "$1$2$3")


INSTRUCT = Template(
    marks=(("user", "[INST] ", " [/INST]"), ("assistant", "<s> ", " </s>"), ("system", "<<SYS>> ", " <</SYS>>")),
    other=("[ROLE] ", " [TEXT] ", " [/ROLE]"),
    first=r"[\[<]",
    rest=r"/?(?:INST|ROLE|TEXT)\]|/?s>|</?SYS>>",
)


def formatted(conversations: DataFrame, template: Template = INSTRUCT, train_on: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """conversations with ``formatted`` and ``loss_spans`` from ``turns``.

    loss_spans: (start, end) code-point ranges of ``formatted`` that are trained on: the escaped texts of turns whose
    role is in ``train_on``, without their marks. No turns: an empty string and no span. Columns with these names
    give way.
    """

    def rendered(t: Column) -> Column:
        known = F.lit(None).cast("struct<o:string,c:string>")
        for role, a, b in template.marks:
            known = F.when(t["role"] == role, F.struct(F.lit(a).alias("o"), F.lit(b).alias("c"))).otherwise(known)
        role = template.escaped(t["role"])
        o = F.coalesce(known["o"], F.concat(F.lit(template.other[0]), role, F.lit(template.other[1])))
        return F.struct(o.alias("o"), template.escaped(t["text"]).alias("x"), F.coalesce(known["c"], F.lit(template.other[2])).alias("c"), t["role"].isin(*train_on).alias("on"))

    kept = [c for c in conversations.columns if c not in ("formatted", "loss_spans")]
    parts = conversations.select(*kept, F.transform("turns", rendered).alias("_parts"))
    whole = F.array_join(F.transform("_parts", lambda p: F.concat(p["o"], p["x"], p["c"])), "")
    empty = F.array().cast("array<struct<start:int,end:int>>")
    start = F.struct(F.lit(0).alias("at"), empty.alias("spans"))

    def step(state: Column, p: Column) -> Column:
        begin = state["at"] + F.length(p["o"])
        end = begin + F.length(p["x"])
        more = F.when(p["on"], F.concat(state["spans"], F.array(F.struct(begin.alias("start"), end.alias("end"))))).otherwise(state["spans"])
        return F.struct((end + F.length(p["c"])).alias("at"), more.alias("spans"))

    return parts.select(*kept, whole.alias("formatted"), F.aggregate("_parts", start, step)["spans"].alias("loss_spans"))


def read_back(rendered: Column, template: Template = INSTRUCT) -> Column:
    """The turns that ``formatted`` rendered: cut before each opening mark, marks taken off, texts unescaped."""
    import re

    opens = "|".join(re.escape(a).replace("\\ ", " ") for a in [*[m[1] for m in template.marks], template.other[0]])
    pieces = F.filter(F.split(rendered, f"(?={opens})"), lambda p: p != "")

    def turn(p: Column) -> Column:
        a, b, c = template.other
        body = F.substr(p, F.lit(len(a) + 1), F.length(p) - len(a) - len(c))
        middle = F.locate(b, body)
        out = F.struct(template.unescaped(F.substr(body, F.lit(1), middle - 1)).alias("role"), template.unescaped(F.substr(body, middle + len(b), F.length(body))).alias("text"))
        for role, o, e in template.marks:
            text = F.substr(p, F.lit(len(o) + 1), F.length(p) - len(o) - len(e))
            out = F.when(p.startswith(o), F.struct(F.lit(role).alias("role"), template.unescaped(text).alias("text"))).otherwise(out)
        return out

    return F.transform(pieces, turn)


def loss_text(rendered: Column, spans: Column, template: Template = INSTRUCT) -> Column:
    """All text under the loss mask, unescaped, in order."""
    return F.array_join(F.transform(spans, lambda s: template.unescaped(F.substr(rendered, s["start"] + 1, s["end"] - s["start"]))), "")
