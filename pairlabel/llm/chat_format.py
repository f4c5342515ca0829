"""Chat formatting by a declarative template and a finite-state machine over roles; DataFrame functions only.

Each turn gives three segments: the marks before it, its escaped text, and the
marks after it, each with a loss flag. The machine's state is the last role seen;
a turn is valid if the template allows the step from the state before it.

Escaping is reversible: the escape sign is doubled, and a control string inside a
text is broken after its first character by the escape sign and a dot, so no
control string of the template ever stands inside a text.

Defined results: null text and null role count as empty; turns with equal numbers
are ordered by role, then text; a role the template does not name gets the
general marks, is never valid and bears no loss; rows with a null conv_id form
one conversation; an empty table gives an empty result; columns other than
conv_id, turn, role and text play no part.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

ESCAPE = "\\"


@dataclass(frozen=True)
class Template:
    """before/after: marks by role; other: marks of further roles, whose name stands between the first two."""

    before: dict[str, str] = field(default_factory=lambda: {"system": "<<SYS>>", "user": "[INST]", "assistant": "<s>"})
    after: dict[str, str] = field(default_factory=lambda: {"system": "<</SYS>>", "user": "[/INST]", "assistant": "</s>"})
    other: tuple[str, str, str] = ("<|role:", "|>", "<|end|>")
    loss_roles: tuple[str, ...] = ("assistant",)
    #: Allowed steps from role to role; None: the start.
    steps: tuple[tuple[str | None, str], ...] = ((None, "system"), (None, "user"), ("system", "user"), ("user", "assistant"), ("assistant", "user"))
    final: tuple[str, ...] = ("assistant",)

    def controls(self) -> list[str]:
        return sorted({*self.before.values(), *self.after.values(), *self.other}, key=lambda x: (-len(x), x))


INSTRUCT = Template()
CHATML = Template(
    before={r: f"<|im_start|>{r}\n" for r in ("system", "user", "assistant")},
    after={r: "<|im_end|>\n" for r in ("system", "user", "assistant")},
)


def _java(text: str) -> str:
    return re.sub(r"([\\\[\](){}.*+?^$|<>/!=-])", r"\\\1", text)


def escape(text: Column, template: Template = INSTRUCT) -> Column:
    doubled = F.replace(text, F.lit(ESCAPE), F.lit(ESCAPE * 2))
    inside = "|".join(f"(?<={_java(c[0])}){_java(c[1:])}" if len(c) > 1 else _java(c) for c in template.controls())
    return F.regexp_replace(doubled, f"({inside})", r"\\.$1")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"\\(\\)|\\\.", "$1")


def segments(conversations: DataFrame, template: Template = INSTRUCT) -> DataFrame:
    """Rows conv_id, turn_no (from 0), part (0 before, 1 text, 2 after), segment, loss, valid."""
    rows = conversations.select(
        "conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")
    )
    w = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    rows = rows.withColumn("turn_no", F.row_number().over(w) - 1).withColumn("last", F.lag("role").over(w))
    allowed = F.lit(False)
    for a, b in template.steps:
        allowed = allowed | ((F.col("last").isNull() if a is None else F.coalesce(F.col("last") == a, F.lit(False))) & (F.col("role") == b))
    return rows.select("conv_id", "turn_no", "role", allowed.alias("valid"), F.explode(_parts(template)).alias("s")).select(
        "conv_id", "turn_no", "s.part", "s.segment", "s.loss", "valid"
    )


def _parts(template: Template) -> Column:
    a, b, c = template.other
    before = F.concat(F.lit(a), escape(F.col("role"), template), F.lit(b))
    after = F.lit(c)
    for role, mark in template.before.items():
        before = F.when(F.col("role") == role, F.lit(mark)).otherwise(before)
        after = F.when(F.col("role") == role, F.lit(template.after[role])).otherwise(after)
    none = F.lit(False)
    return F.array(
        F.struct(F.lit(0).alias("part"), before.alias("segment"), none.alias("loss")),
        F.struct(F.lit(1).alias("part"), escape(F.col("text"), template).alias("segment"), F.col("role").isin(*template.loss_roles).alias("loss")),
        F.struct(F.lit(2).alias("part"), after.alias("segment"), none.alias("loss")),
    )


def formatted(conversations: DataFrame, template: Template = INSTRUCT) -> DataFrame:
    """One row per conversation: conv_id, formatted (the whole string), spans (length, loss per segment), valid, complete."""
    rows = segments(conversations, template)
    ordered = F.array_sort(F.collect_list(F.struct("turn_no", "part", "segment", "loss")))
    by_conv = rows.groupBy("conv_id").agg(ordered.alias("s"), F.min("valid").alias("valid"))
    out = by_conv.withColumn("formatted", F.array_join("s.segment", ""))
    lengths = F.transform("s", lambda x: F.struct(F.length(x["segment"]).cast("bigint").alias("length"), x["loss"].alias("loss")))
    out = out.withColumn("spans", lengths)
    end = F.element_at(F.col("s.segment"), -1)
    complete = F.lit(False)
    for role in template.final:
        complete = complete | (end == template.after[role])
    return out.select("conv_id", "formatted", "spans", "valid", complete.alias("complete"))


def read_back(texts: DataFrame, template: Template = INSTRUCT) -> DataFrame:
    """conv_id, formatted, spans, slices (the formatted string cut into turns), turns (array of role and text), all read from the formatted string."""
    before, after = template.before, template.after
    pieces = [f"{_java(before[r])}(.*?){_java(after[r])}" for r in before]
    a, b, c = template.other
    pieces.append(f"{_java(a)}(.*?){_java(b)}(.*?){_java(c)}")
    turn = "(?s)" + "|".join(pieces)
    whole = F.regexp_extract_all("formatted", F.lit(f"(?s)({turn[4:]})"), F.lit(1))

    def role_text(x: Column) -> Column:
        inner = x.substr(F.locate(b, x) + len(b), F.length(x))
        role = unescape(x.substr(F.lit(len(a) + 1), F.locate(b, x) - len(a) - 1))
        text = inner.substr(F.lit(1), F.length(inner) - len(c))
        out = F.struct(role.alias("role"), text.alias("text"))
        for r in before:
            text = x.substr(F.lit(len(before[r]) + 1), F.length(x) - len(before[r]) - len(after[r]))
            out = F.when(x.startswith(before[r]), F.struct(F.lit(r).alias("role"), text.alias("text"))).otherwise(out)
        return out

    turns = F.transform(F.transform("slices", role_text), lambda t: F.struct(t["role"].alias("role"), unescape(t["text"]).alias("text")))
    return texts.withColumn("slices", whole).withColumn("turns", turns)


def loss_text(slices: Column, spans: Column) -> Column:
    """What the loss mask covers of the formatted string, unescaped: each turn's slice is cut at the lengths that its three spans record, and the cuts under the mask follow each other.

    Slices that do not have their spans' length stop the job: the mask would then cover other text.
    """

    def under(x: Column, i: Column) -> Column:
        own = [F.get(spans, i * 3 + k) for k in range(3)]
        at, cuts = F.lit(1), []
        for span in own:
            cuts.append(F.when(span["loss"], x.substr(at.cast("int"), span["length"].cast("int"))).otherwise(""))
            at = at + span["length"]
        return F.when(F.length(x) + 1 == at, F.concat(*cuts)).otherwise(F.raise_error(F.lit("a turn's length differs from its spans")).cast("string"))

    return unescape(F.array_join(F.transform(slices, under), ""))
