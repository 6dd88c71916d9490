"""What every operator offers to the compiler, and the registry of operators by signature.

``vector(x)`` maps an n x inputs matrix to n x outputs; ``expr(cols)`` does the same with
Spark columns, or raises :class:`NoExpression`.  ``restrict(outputs)`` gives the operator that
makes only some of the outputs, and the inputs it still needs - or None where the
selection must stay above (a blocking operator).
"""

from __future__ import annotations

from collections.abc import Callable
from contextlib import contextmanager
from contextvars import ContextVar
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column

REGISTRY: dict[str, Callable[..., Operator]] = {}


class NoExpression(NotImplementedError):
    """The operator has no form of built-in columns."""


class UnknownSignature(KeyError):
    pass


def converter(signature: str):
    """Register the maker of an operator; users may add their own."""

    def add(make):
        REGISTRY[signature] = make
        make.signature = signature
        return make

    return add


def lower(signature: str, **params) -> Operator:
    if signature not in REGISTRY:
        raise UnknownSignature(signature)
    return REGISTRY[signature](**params)


@dataclass
class Operator:
    def width(self, inputs: int) -> int:
        return inputs

    def vector(self, x: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def expr(self, xs: list[Column]) -> list[Column]:
        raise NoExpression(type(self).__name__)

    def restrict(self, outputs: list[int], inputs: int) -> tuple[Operator, list[int]] | None:
        return None

    #: Calls of bulk primitives for a batch.
    calls = 1


#: The type that operators compute in; see ``precision``.
_KIND: ContextVar[type] = ContextVar("kind", default=np.float64)


@contextmanager
def precision(kind: type):
    """Operators compute in this floating type inside the block."""
    token = _KIND.set(kind)
    try:
        yield
    finally:
        _KIND.reset(token)


def array(values) -> np.ndarray:
    return np.asarray(values, _KIND.get())


def nonzero(scale) -> np.ndarray:
    """Scales of constant columns count as 1."""
    s = array(scale)
    return np.where(s == 0, 1.0, s)
