"""Chat formatting by schema fingerprints.

A record's fingerprint is the sha256 of its sorted nested field paths that hold a value.  A
registry maps fingerprints to declarative mappings, each a list of (role, path) rules or
one list-of-turns rule; so prompt and completion pairs, instruction records, question and
answer records and several message layouts all become canonical turns (role, text).
Canonical turns are written with marks around each turn.  Inside texts and roles the
escape sign and the mark opener are rewritten, so no text can hold a mark, and reading
back undoes it exactly.  The loss mask is a list of (start, length) in code points.

Defined cases: a null text is empty and a null role is ``user``; turns that tie in number
are ordered by role, then text; an unknown fingerprint gives no turns and is reported in
``mapping`` as null; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

OPEN, CLOSE, ESCAPE = "<|im_start|>", "<|im_end|>", "\\"
# What is rewritten in texts; the order undoes it safely.
TEXT_RULES = (("\\", "\\5C"), ("<|", "\\3C|"))
ROLE_RULES = (*TEXT_RULES, ("\n", "\\0A"))


def escape(c: Column, rules=TEXT_RULES) -> Column:
    for raw, safe in rules:
        c = F.replace(c, F.lit(raw), F.lit(safe))
    return c


def unescape(c: Column, rules=TEXT_RULES) -> Column:
    for raw, safe in reversed(rules):
        c = F.replace(c, F.lit(safe), F.lit(raw))
    return c


# ---- schema fingerprints -------------------------------------------------------------


def paths_of(schema: T.DataType, prefix: str = "") -> list[str]:
    """Nested leaf paths; a list element is written ``[]``."""
    if isinstance(schema, T.StructType):
        return [p for f in schema.fields for p in paths_of(f.dataType, f"{prefix}.{f.name}" if prefix else f.name)]
    if isinstance(schema, T.ArrayType):
        return paths_of(schema.elementType, f"{prefix}[]")
    return [prefix]


def fingerprint_of(paths) -> str:
    return hashlib.sha256("\n".join(sorted(paths)).encode()).hexdigest()


def _has(path: str) -> Column:
    """Whether a path holds a value in a row."""
    head, _, tail = path.partition("[]")
    c = F.col(head)
    if tail:
        return F.coalesce(F.exists(c, lambda x: x[tail.lstrip(".")].isNotNull()), F.lit(False))
    return F.coalesce(F.size(c) > 0, F.lit(False)) if "[]" in path else c.isNotNull()


def row_fingerprint(df: DataFrame, ignore: tuple[str, ...] = ()) -> Column:
    """Fingerprint of the paths that a row fills, so one table may mix layouts."""
    paths = [p for p in sorted(paths_of(df.schema)) if p.split(".")[0].split("[")[0] not in ignore]
    return F.sha2(F.concat_ws("\n", *[F.when(_has(p), F.lit(p)) for p in paths]), 256)


@dataclass(frozen=True)
class Mapping:
    """``turns``: (list path, role field, text field); or ``fields``: (role, path) in order."""

    name: str
    turns: tuple[str, str, str] | None = None
    order: str | None = None
    fields: tuple[tuple[str, str], ...] = ()
    optional: tuple[str, ...] = ()

    def fingerprints(self) -> list[str]:
        if self.turns:
            at, role, text = self.turns
            base = [f"{at}[].{x}" for x in (role, text, *([self.order] if self.order else []))]
            return [fingerprint_of(base)]
        must = [p for _, p in self.fields if p not in self.optional]
        spare = [p for _, p in self.fields if p in self.optional]
        return [fingerprint_of([*must, *[p for i, p in enumerate(spare) if bits >> i & 1]]) for bits in range(1 << len(spare))]

    def canonical(self, have: set[str]) -> Column | None:
        """array<struct<role, text>> of a row, or None where the table has no such columns."""
        one = lambda r, t: F.struct(r.cast("string").alias("role"), t.cast("string").alias("text"))
        if self.turns:
            at, role, text = self.turns
            if at not in have:
                return None
            c = F.col(at)
            if self.order:
                c = F.array_sort(F.transform(c, lambda x: F.struct(x[self.order].alias("o"), x[role].alias("r"), x[text].alias("t"))))
                return F.transform(c, lambda x: one(F.coalesce(x["r"], F.lit("user")), F.coalesce(x["t"], F.lit(""))))
            return F.transform(c, lambda x: one(F.coalesce(x[role], F.lit("user")), F.coalesce(x[text], F.lit(""))))
        got = [(r, p) for r, p in self.fields if p.split(".")[0] in have]
        if any(p not in self.optional and p not in [q for _, q in got] for _, p in self.fields):
            return None
        return F.filter(F.array(*[F.when(F.col(p).isNotNull(), one(F.lit(r), F.col(p))) for r, p in got]), lambda x: x.isNotNull())


#: The layouts known at the start; ``to_turns`` takes any other registry.
REGISTRY = (
    Mapping("turn_rows", turns=("turns", "role", "text"), order="turn"),
    Mapping("messages", turns=("messages", "role", "content")),
    Mapping("from_value", turns=("conversations", "from", "value")),
    Mapping("prompt_completion", fields=(("user", "prompt"), ("assistant", "completion"))),
    Mapping("prompt_response", fields=(("system", "system"), ("user", "prompt"), ("assistant", "response")), optional=("system",)),
    Mapping("instruction", fields=(("system", "instruction"), ("user", "input"), ("assistant", "output")), optional=("input",)),
    Mapping("question_answer", fields=(("user", "question"), ("assistant", "answer"))),
)
#: Other names of roles.
ROLE_NAMES = {"human": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant"}


def to_turns(df: DataFrame, key: str, registry=REGISTRY, rename_roles: bool = True) -> DataFrame:
    """(key, mapping, turns) with the mapping that the row's fingerprint selects."""
    have = set(df.columns)
    mark = row_fingerprint(df, (key,))
    name, turns = F.lit(None).cast("string"), F.lit(None).cast("array<struct<role:string,text:string>>")
    for m in registry:
        c = m.canonical(have - {key})
        if c is not None:
            hit = F.col("fingerprint").isin(m.fingerprints())
            name, turns = F.when(hit, F.lit(m.name)).otherwise(name), F.when(hit, c).otherwise(turns)
    out = df.withColumn("fingerprint", mark).select(F.col(key), "fingerprint", name.alias("mapping"), turns.alias("turns"))
    if rename_roles:
        role = F.create_map(*[F.lit(x) for kv in ROLE_NAMES.items() for x in kv])
        out = out.withColumn("turns", F.transform("turns", lambda x: F.struct(F.coalesce(role[x["role"]], x["role"]).alias("role"), x["text"].alias("text"))))
    return out


def gather_turns(rows: DataFrame, key: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """Row-by-turn tables as records of the ``turn_rows`` layout, nulls made plain."""
    one = F.struct(F.coalesce(F.col(turn), F.lit(-1)).cast("bigint").alias("turn"), F.coalesce(F.col(role), F.lit("user")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    return rows.groupBy(key).agg(F.collect_list(one).alias("turns"))


# ---- template ----------------------------------------------------------------------------


def render(turned: DataFrame, learn: str = "assistant") -> DataFrame:
    """Adds ``formatted`` and ``loss_spans`` (start from 1, length) over it, in code points."""
    head = lambda x: F.concat(F.lit(OPEN), escape(x["role"], ROLE_RULES), F.lit("\n"))
    piece = lambda x: F.concat(head(x), escape(x["text"]), F.lit(CLOSE + "\n"))
    out = turned.withColumn("formatted", F.array_join(F.transform("turns", piece), ""))
    zero = F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast("array<struct<start:bigint,length:bigint>>").alias("spans"))

    def step(acc, x):
        start = acc["at"] + F.char_length(head(x))
        n = F.char_length(escape(x["text"])).cast("bigint")
        span = F.struct((start + 1).cast("bigint").alias("start"), n.alias("length"))
        return F.struct((start + n + len(CLOSE) + 1).cast("bigint").alias("at"), F.when(x["role"] == learn, F.concat(acc["spans"], F.array(span))).otherwise(acc["spans"]).alias("spans"))

    return out.withColumn("loss_spans", F.aggregate("turns", zero, step)["spans"])


def parse(formatted: Column) -> Column:
    """Turns read back from a formatted string."""
    parts = F.filter(F.split(formatted, r"<\|im_start\|>", -1), lambda p: p != "")

    def turn(p):
        cut = F.instr(p, "\n")
        body = F.substring(p, cut + 1, F.char_length(p) - cut - len(CLOSE) - 1)
        return F.struct(unescape(F.substring(p, F.lit(1), cut - 1), ROLE_RULES).alias("role"), unescape(body).alias("text"))

    return F.transform(parts, turn)


def masked_text(formatted: Column, spans: Column) -> Column:
    """All text under the loss mask, unescaped, nothing between."""
    return F.array_join(F.transform(spans, lambda s: unescape(F.substring(formatted, s["start"].cast("int"), s["length"].cast("int")))), "")
