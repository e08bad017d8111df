"""Instruction templates: natural-language text with column slots."""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

_PART = re.compile(r"\{\{|\}\}|\{([^{}]*)\}|[{}]")
SIDES = ("left", "right")


class TemplateError(ValueError):
    pass


@dataclass(frozen=True)
class Slot:
    column: str
    side: str | None = None


@dataclass(frozen=True)
class Template:
    """Text such as ``"{text} is junk"`` or, for two tables, ``"{text:left} cites {title:right}"``; braces are doubled to escape them."""

    text: str

    @cached_property
    def parts(self) -> tuple[str | Slot, ...]:
        out: list[str | Slot] = []
        at = 0
        for m in _PART.finditer(self.text):
            out.append(self.text[at : m.start()])
            at = m.end()
            if m.group() in ("{{", "}}"):
                out.append(m.group()[0])
            elif m.group(1) is None:
                raise TemplateError(f"unbalanced brace at {m.start()} in {self.text!r}")
            else:
                name, _, side = m.group(1).partition(":")
                name, side = name.strip(), side.strip() or None
                if not name or side not in (None, *SIDES):
                    raise TemplateError(f"bad slot {m.group()!r}")
                out.append(Slot(name, side))
        out.append(self.text[at:])
        return tuple(p for p in out if p != "")

    @property
    def slots(self) -> tuple[Slot, ...]:
        return tuple(dict.fromkeys(p for p in self.parts if isinstance(p, Slot)))

    def bind(self, df: DataFrame) -> "Template":
        """Check a one-table template against a schema."""
        if any(s.side for s in self.slots):
            raise TemplateError("a one-table template takes no sides")
        self._check([s.column for s in self.slots], df)
        return self

    def bind_pair(self, left: DataFrame, right: DataFrame) -> "Template":
        if {s.side for s in self.slots} != set(SIDES):
            raise TemplateError("a pair template needs :left and :right slots, and no others")
        self._check([s.column for s in self.slots if s.side == "left"], left)
        self._check([s.column for s in self.slots if s.side == "right"], right)
        return self

    @staticmethod
    def _check(names: list[str], df: DataFrame) -> None:
        if missing := [n for n in names if n not in df.columns]:
            raise TemplateError(f"no such columns: {missing}; there are {df.columns}")
        if binary := [n for n in names if isinstance(df.schema[n].dataType, T.BinaryType)]:
            raise TemplateError(f"media slots need a model that takes media: {binary}")

    def columns(self, side: str | None = None) -> list[str]:
        return [s.column for s in self.slots if s.side == side]

    def prompt(self, df: DataFrame, name_of=lambda s: s.column) -> Column:
        """The rendered prompt; null if a slot is null."""
        shown = []
        for p in self.parts:
            if isinstance(p, str):
                shown.append(F.lit(p))
            else:
                column = name_of(p)
                kind = df.schema[column].dataType
                nested = isinstance(kind, T.ArrayType | T.MapType | T.StructType)
                shown.append(F.to_json(F.col(column)) if nested else F.col(column).cast("string"))
        return F.concat(*shown) if shown else F.lit("")

    def has_null(self, name_of=lambda s: s.column) -> Column:
        out = F.lit(False)
        for s in self.slots:
            out = out | F.col(name_of(s)).isNull()
        return out
