"""Targets of a program divided over its operators."""

from __future__ import annotations

import threading
from contextlib import contextmanager

from ..result import GuaranteeSpec

_state = threading.local()


def split_budget(spec: GuaranteeSpec, operators: int) -> GuaranteeSpec:
    """Each operator's share: failure probabilities add up, targets multiply."""
    if operators < 1:
        raise ValueError("at least one operator")
    root = lambda x: None if x is None else x ** (1 / operators)
    return GuaranteeSpec(root(spec.recall), root(spec.precision), root(spec.accuracy), spec.delta / operators)


@contextmanager
def guarantee(operators: int, **targets):
    """Within the block, ``current()`` is each operator's share of the program's targets."""
    before = getattr(_state, "spec", None)
    _state.spec = split_budget(GuaranteeSpec(**targets), operators)
    try:
        yield _state.spec
    finally:
        _state.spec = before


def current() -> GuaranteeSpec | None:
    return getattr(_state, "spec", None)
