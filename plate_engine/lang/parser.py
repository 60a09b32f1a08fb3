"""A small text form of the model language.

    model lda(K: long, V: long, alpha: double, beta: double) {
      plate topics = 0 until K
      plate docs = ?
      plate words = ? in docs
      phi[topics] ~ Dirichlet(beta, V)
      theta[docs] ~ Dirichlet(alpha, K)
      z[words] ~ Categorical(theta)
      x[words] ~ Categorical(phi[z])
    }

``a to b`` is the inclusive range, ``_ ~`` leaves a variable nameless, ``{ ... }`` opens a scope.
"""

from __future__ import annotations

import re

from .builder import Expr, ModelError, ModelSpec, Plate, Rv

TOKEN = re.compile(r"\s*(?:(//[^\n]*)|(\d+\.\d*(?:[eE][-+]?\d+)?|\d+)|([A-Za-z_]\w*)|(.))")


class _Reader:
    def __init__(self, text: str):
        self.tokens = [(m.group(2) and "number" or m.group(3) and "name" or "sign", m.group(2) or m.group(3) or m.group(4), text.count("\n", 0, m.start(m.lastindex)) + 1) for m in TOKEN.finditer(text) if m.group(2) or m.group(3) or (m.group(4) and m.group(4).strip())]
        self.at = 0

    def peek(self, k: int = 0) -> str:
        return self.tokens[self.at + k][1] if self.at + k < len(self.tokens) else ""

    def fail(self, wanted: str) -> ModelError:
        line = self.tokens[min(self.at, len(self.tokens) - 1)][2] if self.tokens else 0
        return ModelError(f"line {line}: {wanted} expected, found {self.peek() or 'the end'!r}")

    def take(self, wanted: str | None = None, kind: str | None = None) -> str:
        if self.at >= len(self.tokens) or (wanted and self.peek() != wanted) or (kind and self.tokens[self.at][0] != kind):
            raise self.fail(wanted or kind or "more")
        self.at += 1
        return self.tokens[self.at - 1][1]

    def had(self, wanted: str) -> bool:
        if self.peek() == wanted:
            self.at += 1
            return True
        return False


def parse_model(text: str) -> ModelSpec:
    r = _Reader(text)
    r.take("model")
    name, params = r.take(kind="name"), {}
    if r.had("("):
        while not r.had(")"):
            p = r.take(kind="name")
            r.take(":")
            kind = r.take(kind="name")
            if kind not in ("long", "double"):
                raise ModelError(f"parameter {p!r} has the type {kind!r}; long and double are possible")
            params[p] = int if kind == "long" else float
            r.had(",")
    spec = ModelSpec(name, params)
    _block(r, spec)
    if r.peek():
        raise r.fail("the end")
    return spec


def _block(r: _Reader, spec: ModelSpec) -> None:
    r.take("{")
    while not r.had("}"):
        if r.peek() == "{":
            with spec.scope():
                _block(r, spec)
        elif r.had("plate"):
            _plate(r, spec)
        else:
            _variable(r, spec)


def _plate(r: _Reader, spec: ModelSpec) -> None:
    name = r.take(kind="name")
    r.take("=")
    size, lo, inclusive = None, 0, False
    if not r.had("?"):
        lo = _sum(r, spec)
        inclusive = r.take(kind="name") == "to"
        size = _sum(r, spec)
    parent = spec[r.take(kind="name")] if r.had("in") else None
    spec.plate(name, size, lo, inclusive, parent)


def _variable(r: _Reader, spec: ModelSpec) -> None:
    name = r.take(kind="name")
    plate = None
    if r.had("["):
        plate = spec[r.take(kind="name")]
        if not isinstance(plate, Plate):
            raise ModelError(f"{name!r} is repeated over something that is no plate")
        r.take("]")
    if r.had("="):
        spec.alias(name, spec[r.take(kind="name")])
        return
    r.take("~")
    kind = r.take(kind="name")
    name = None if name == "_" else name
    r.take("(")
    if kind == "Dirichlet":
        concentration = _sum(r, spec)
        r.take(",")
        spec.dirichlet(name, concentration, _sum(r, spec), plate)
    elif kind == "Beta":
        spec.beta(name, _sum(r, spec), plate)
    elif kind == "Categorical":
        prior = spec[r.take(kind="name")]
        if not isinstance(prior, Rv):
            raise ModelError("a categorical variable needs a probability variable")
        selectors = []
        while r.had("["):
            selectors.append(spec[r.take(kind="name")])
            r.take("]")
        spec.categorical(name, prior.at(*selectors) if selectors else prior, plate)
    else:
        raise ModelError(f"{kind!r} isn't a supported distribution")
    r.take(")")


def _sum(r: _Reader, spec: ModelSpec) -> Expr:
    left = _product(r, spec)
    while r.peek() in ("+", "-"):
        left = left + _product(r, spec) if r.take() == "+" else left - _product(r, spec)
    return left


def _product(r: _Reader, spec: ModelSpec) -> Expr:
    left = _atom(r, spec)
    while r.peek() in ("*", "/"):
        left = left * _atom(r, spec) if r.take() == "*" else left / _atom(r, spec)
    return left


def _atom(r: _Reader, spec: ModelSpec) -> Expr:
    if r.had("-"):
        return -_atom(r, spec)
    if r.had("+"):
        return _atom(r, spec)
    if r.had("("):
        got = _sum(r, spec)
        r.take(")")
        return got
    token = r.take()
    if re.fullmatch(r"\d+", token):
        return Expr.of(int(token))
    if re.match(r"\d", token):
        return Expr.of(float(token))
    value = spec[token]
    if not isinstance(value, Expr):
        raise ModelError(f"{token!r} isn't a constant")
    return value
