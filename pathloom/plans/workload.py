"""Seeded generator of views: unions of conjunctions of two-way paths, some of whose steps are closures."""

from __future__ import annotations

import random

from .rules import Program, program


def random_path(rng: random.Random, schema: dict[str, tuple[str, str]], start: str, length: int, p_closure: float) -> tuple[str, str] | None:
    """(path, kind of node it ends at) of a walk over the schema; None if it cannot go on."""
    steps, at = [], start
    for _ in range(length):
        ways = [(x, False) for x, (a, _) in schema.items() if a == at] + [(x, True) for x, (_, b) in schema.items() if b == at]
        if not ways:
            return None
        label, back = rng.choice(sorted(ways))
        a, b = schema[label]
        step = f"~{label}" if back else label
        if a == b and rng.random() < p_closure:
            step = f"({step})+" if back else f"{step}+"
        steps.append(step)
        at = a if back else b
    return "/".join(steps), at


def random_views(schema: dict[str, tuple[str, str]], n: int = 10, seed: int = 42, max_len: int = 3, p_closure: float = 0.5, p_union: float = 0.3, p_and: float = 0.2) -> dict[str, Program]:
    """n programs of one view each, by name. schema: label to the kinds of its ends, so that paths fit together."""
    rng, out = random.Random(seed), {}
    kinds = sorted({k for ends in schema.values() for k in ends})
    while len(out) < n:
        start = rng.choice(kinds)
        first = random_path(rng, schema, start, rng.randint(1, max_len), p_closure)
        if first is None:
            continue
        text, end = first
        for mark, p in ((" & ", p_and), (" | ", p_union)):
            if rng.random() < p:
                others = [random_path(rng, schema, start, rng.randint(1, max_len), p_closure) for _ in range(20)]
                fit = [o[0] for o in others if o is not None and o[1] == end and o[0] != text]
                text = f"({text}){mark}({fit[0]})" if fit else text
        name = f"w{len(out) + 1}"
        out[name] = program({name: text})
    return out
