"""Path rules: binary, non-recursive clauses whose only recursion is a closure mark on a literal.

Terms, literals, clauses and programs are plain frozen values on the driver; no Spark job runs here. Literals carry a
tag, so that plain bodies and delta-rewritten ones (OLD, DELTA, NEW) are the same classes.
"""

from __future__ import annotations

import re
from collections.abc import Iterable
from dataclasses import dataclass, field, replace
from itertools import count, product


@dataclass(frozen=True)
class Var:
    name: str


@dataclass(frozen=True)
class Const:
    id: int


Term = Var | Const


@dataclass(frozen=True)
class Rel:
    label: str
    a: Term
    b: Term

    @property
    def terms(self) -> tuple[Term, Term]:
        return self.a, self.b


@dataclass(frozen=True)
class Eq:
    a: Term
    b: Term

    @property
    def terms(self) -> tuple[Term, Term]:
        return self.a, self.b


@dataclass(frozen=True)
class Lit:
    atom: Rel | Eq
    closed: bool = False
    tag: str | None = None

    def __post_init__(self):
        if isinstance(self.atom, Eq) and self.closed:
            object.__setattr__(self, "closed", False)  # equality is its own closure

    def with_tag(self, tag: str | None) -> Lit:
        return replace(self, tag=tag)

    @property
    def symbol(self) -> tuple[str, bool] | None:
        return None if isinstance(self.atom, Eq) else (self.atom.label, self.closed)


Conj = tuple[Lit, ...]


@dataclass(frozen=True)
class Clause:
    head: tuple[Var, Var]
    bodies: tuple[Conj, ...]


@dataclass(frozen=True)
class Program:
    clauses: dict[str, Clause] = field(default_factory=dict)

    def is_base(self, label: str) -> bool:
        return label not in self.clauses

    def base_labels(self) -> set[str]:
        return {s for c in self.clauses.values() for s in symbols_of(c)} - set(self.clauses) - {NODES}

    def closed_labels(self) -> set[str]:
        return {lit.atom.label for c in self.clauses.values() for b in c.bodies for lit in b if lit.closed}


@dataclass(frozen=True)
class ViewQuery:
    program: Program
    view: str


#: The label of the node domain, pairs (node, node); no rule text can name it.
NODES = "@nodes"


class RuleError(ValueError):
    """A rule that the language does not have; the message names the reason."""


def symbols_of(x: Clause | Conj) -> set[str]:
    """Labels in a body or clause."""
    bodies = x.bodies if isinstance(x, Clause) else (x,)
    return {lit.atom.label for b in bodies for lit in b if isinstance(lit.atom, Rel)}


def variables(conj: Conj) -> list[str]:
    return list(dict.fromkeys(t.name for lit in conj for t in lit.atom.terms if isinstance(t, Var)))


# ---- rule text

@dataclass(frozen=True)
class RawLit:
    label: str | None  # None: equality
    a: Term
    b: Term
    inverse: bool = False
    mark: str = ""  # "", "+" or "*"


@dataclass(frozen=True)
class RawRule:
    head: str
    a: Term
    b: Term
    body: tuple[RawLit, ...]


_lit = re.compile(r"\s*(?:(?P<inv>~)?(?P<label>[A-Za-z_]\w*)(?P<mark>[+*]?)\(\s*(?P<a>\w+)\s*,\s*(?P<b>\w+)\s*\)|(?P<c>\w+)\s*=\s*(?P<d>\w+))\s*(?:,|$)")


def _term(s: str) -> Term:
    return Const(int(s)) if s.isdigit() else Var(s)


def parse_rules(text: str) -> list[RawRule]:
    """Rules `head(X, Y) :- a(X, Z), ~b+(Z, Y), X = Z.`; a fact is `a(1, 2).`; # begins a comment."""
    out = []
    for part in re.sub(r"#.*", "", text).split("."):
        if not part.strip():
            continue
        head, _, body = part.partition(":-")
        m = _lit.fullmatch(head)
        if not m or not m["label"] or m["inv"] or m["mark"]:
            raise RuleError(f"not a head: {head.strip()}")
        lits, at = [], 0
        while body[at:].strip():
            if not (k := _lit.match(body, at)):
                raise RuleError(f"not a literal: {body[at:].strip()}")
            lits.append(RawLit(None, _term(k["c"]), _term(k["d"])) if k["c"] else RawLit(k["label"], _term(k["a"]), _term(k["b"]), bool(k["inv"]), k["mark"]))
            at = k.end()
        out.append(RawRule(m["label"], _term(m["a"]), _term(m["b"]), tuple(lits)))
    return out


def expand_sugar(body: tuple[RawLit, ...]) -> list[Conj]:
    """Inverse swaps arguments; a reflexive closure is an equality or a closure, so a body can become several."""
    options = []
    for lit in body:
        a, b = (lit.b, lit.a) if lit.inverse else (lit.a, lit.b)
        if lit.label is None:
            options.append([Lit(Eq(a, b))])
        else:
            options.append([Lit(Rel(lit.label, a, b), bool(lit.mark))] + [Lit(Eq(a, b))] * (lit.mark == "*"))
    return [tuple(choice) for choice in product(*options)]


def renamed(conj: Conj, names: dict[Var, Term]) -> Conj:
    sub = lambda t: names.get(t, t) if isinstance(t, Var) else t
    return tuple(replace(lit, atom=replace(lit.atom, a=sub(lit.atom.a), b=sub(lit.atom.b))) for lit in conj)


def complete(rules: Iterable[RawRule]) -> Program:
    """One clause for each head label: a common head pair, constants and repeated head variables as equalities."""
    x, y = Var("X"), Var("Y")
    bodies: dict[str, list[Conj]] = {}
    for rule in rules:
        for conj in expand_sugar(rule.body):
            fresh = {Var(v): Var(f"{v}_") for v in variables(conj) + [t.name for t in (rule.a, rule.b) if isinstance(t, Var)]}
            conj = renamed(conj, fresh)
            names, extra = {}, []
            for own, common in ((rule.a, x), (rule.b, y)):
                own = fresh.get(own, own) if isinstance(own, Var) else own
                if isinstance(own, Const) or own in names:
                    extra.append(Lit(Eq(common, names.get(own, own) if isinstance(own, Var) else own)))
                else:
                    names[own] = common
            bodies.setdefault(rule.head, []).append((*renamed(conj, names), *extra))
    return Program({label: Clause((x, y), tuple(dict.fromkeys(b))) for label, b in bodies.items()})


# ---- path expressions

@dataclass(frozen=True)
class PathExpr:
    """`a / b` composition, `a | b` union, `a & b` intersection, `~a` inverse, .plus() and .star() closures."""

    op: str
    parts: tuple

    def __truediv__(self, other: PathExpr) -> PathExpr:
        return PathExpr("/", (self, other))

    def __or__(self, other: PathExpr) -> PathExpr:
        return PathExpr("|", (self, other))

    def __and__(self, other: PathExpr) -> PathExpr:
        return PathExpr("&", (self, other))

    def __invert__(self) -> PathExpr:
        return PathExpr("~", (self,))

    def plus(self) -> PathExpr:
        return PathExpr("+", (self,))

    def star(self) -> PathExpr:
        return PathExpr("*", (self,))

    def compile(self, label: str) -> Program:
        """A program with the label, and auxiliary labels for closures of composite expressions."""
        clauses: dict[str, Clause] = {}
        numbers, names = count(1), count(1)

        def walk(e: PathExpr, a: Term, b: Term) -> list[Conj]:
            if e.op == "label":
                return [(Lit(Rel(e.parts[0], a, b)),)]
            if e.op == "~":
                return walk(e.parts[0], b, a)
            if e.op == "|":
                return [c for p in e.parts for c in walk(p, a, b)]
            if e.op in "/&":
                middle = Var(f"Z{next(numbers)}") if e.op == "/" else None
                left, right = (walk(e.parts[0], a, middle), walk(e.parts[1], middle, b)) if middle else (walk(p, a, b) for p in e.parts)
                return [(*c, *d) for c in left for d in right]
            inner, flip = e.parts[0], False
            while inner.op == "~":
                inner, flip = inner.parts[0], not flip
            if inner.op != "label":
                aux = f"{label}_aux{next(names)}"
                x, y = Var("X"), Var("Y")
                clauses[aux] = Clause((x, y), tuple(walk(inner, x, y)))
                inner = rel(aux)
            s, t = (b, a) if flip else (a, b)
            return [(Lit(Rel(inner.parts[0], s, t), True),)] + [(Lit(Eq(s, t)),)] * (e.op == "*")

        x, y = Var("X"), Var("Y")
        clauses[label] = Clause((x, y), tuple(dict.fromkeys(walk(self, x, y))))
        return Program(clauses)


def rel(label: str) -> PathExpr:
    return PathExpr("label", (label,))


_path_token = re.compile(r"\s*([A-Za-z_]\w*|[~/|&()+*])")


def parse_path(text: str) -> PathExpr:
    """Path syntax: `~a/b+ | (c & d)*`; closures bind tightest, then ~, /, & and |."""
    tokens, at = [], 0
    while text[at:].strip():
        if not (m := _path_token.match(text, at)):
            raise RuleError(f"not a path: {text[at:]}")
        tokens.append(m[1])
        at = m.end()
    tokens.append("")

    def binary(op: str, inner):
        def parse() -> PathExpr:
            out = inner()
            while tokens[0] == op:
                tokens.pop(0)
                out = PathExpr(op, (out, inner()))
            return out

        return parse

    def unary() -> PathExpr:
        if tokens[0] == "~":
            tokens.pop(0)
            return ~unary()
        t = tokens.pop(0)
        if t == "(":
            out = union()
            if tokens.pop(0) != ")":
                raise RuleError(f"unbalanced: {text}")
        elif t and t not in "/|&)+*":
            out = rel(t)
        else:
            raise RuleError(f"not a path: {text}")
        while tokens[0] in ("+", "*"):
            out = PathExpr(tokens.pop(0), (out,))
        return out

    union = binary("|", binary("&", binary("/", unary)))
    out = union()
    if tokens != [""]:
        raise RuleError(f"not a path: {text}")
    return out


def program(paths: dict[str, str | PathExpr]) -> Program:
    clauses: dict[str, Clause] = {}
    for label, p in paths.items():
        clauses |= (parse_path(p) if isinstance(p, str) else p).compile(label).clauses
    return Program(clauses)


def merged(*programs: Program) -> Program:
    out: dict[str, Clause] = {}
    for p in programs:
        out |= p.clauses
    return Program(out)


# ---- analysis

def check_safe(p: Program, strict: bool = True) -> list[tuple[str, int, str]]:
    """(label, body, variable) of head variables that a body does not bind; not strict: that no body of the clause binds."""
    out = []
    for label, clause in p.clauses.items():
        bound = [bound_vars(b) for b in clause.bodies]
        for v in clause.head:
            for k, own in enumerate(bound if strict else [set().union(*bound)]):
                if v.name not in own:
                    out.append((label, k, v.name))
    return out


def bound_vars(conj: Conj) -> set[str]:
    out = {t.name for lit in conj if isinstance(lit.atom, Rel) for t in lit.atom.terms if isinstance(t, Var)}
    while True:
        more = set()
        for lit in conj:
            if isinstance(lit.atom, Eq):
                a, b = lit.atom.terms
                for s, t in ((a, b), (b, a)):
                    if isinstance(t, Var) and t.name not in out and (isinstance(s, Const) or s.name in out):
                        more.add(t.name)
        if not more:
            return out
        out |= more


def grounded(conj: Conj, head: tuple[Var, Var]) -> Conj:
    """A body with a literal of the node domain for what nothing in it binds, so that new nodes change it like new edges."""
    wanted = [v.name for v in head] + variables(conj)
    while free := [v for v in wanted if v not in bound_vars(conj)]:
        conj = (*conj, Lit(Rel(NODES, Var(free[0]), Var(free[0]))))
    return conj


def grounded_clause(clause: Clause) -> Clause:
    return Clause(clause.head, tuple(grounded(b, clause.head) for b in clause.bodies))


def grounded_program(p: Program) -> Program:
    return Program({label: grounded_clause(c) for label, c in p.clauses.items()})


def stratify(p: Program) -> list[str]:
    """Derived labels in dependency order; any self- or mutual dependency is an error."""
    out: list[str] = []
    state: dict[str, int] = {}

    def visit(label: str, path: tuple[str, ...]) -> None:
        if p.is_base(label) or state.get(label) == 2:
            return
        if state.get(label) == 1:
            raise RuleError(f"recursive labels: {' -> '.join((*path[path.index(label):], label))}")
        state[label] = 1
        for s in sorted(symbols_of(p.clauses[label])):
            visit(s, (*path, label))
        state[label] = 2
        out.append(label)

    for label in sorted(p.clauses):
        visit(label, ())
    return out


def is_stratified(p: Program, done: Iterable[str], todo: Iterable[str]) -> bool:
    seen = set(done)
    for label in todo:
        if label in seen or (label in p.clauses and not symbols_of(p.clauses[label]) <= seen):
            return False
        seen.add(label)
    return True


def is_slice(p: Program, labels: Iterable[str]) -> bool:
    """Whether a set of labels is closed under dependencies."""
    labels = set(labels)
    return all(symbols_of(p.clauses[x]) <= labels for x in labels if x in p.clauses)


def slice_labels(p: Program, view: str) -> set[str]:
    out, todo = set(), [view]
    while todo:
        if (x := todo.pop()) not in out:
            out.add(x)
            todo += symbols_of(p.clauses[x]) if x in p.clauses else []
    return out


def slice_for(query: ViewQuery) -> ViewQuery:
    keep = slice_labels(query.program, query.view)
    return ViewQuery(Program({k: c for k, c in query.program.clauses.items() if k in keep}), query.view)


def is_uc2rpq(query: ViewQuery) -> bool:
    """Unions of conjunctions of two-way steps, plain or closed, without constants."""
    own = slice_for(query).program.clauses.values()
    return all(isinstance(t, Var) for c in own for b in c.bodies for lit in b for t in lit.atom.terms) and not check_safe(Program({str(k): c for k, c in enumerate(own)}), strict=False)


# ---- delta rewriting

OLD, DELTA, NEW = "old", "delta", "new"


def mask_grid(conj: Conj, factoring: str = "old_prefix") -> list[Conj]:
    """Bodies whose union is the change of a body under insertions; each has its delta literals tagged.

    old_prefix: OLD before the delta, NEW after; new_prefix: the mirror; expanded: all combinations of OLD and DELTA
    with a DELTA. Equalities do not change.
    """
    places = [k for k, lit in enumerate(conj) if isinstance(lit.atom, Rel)]
    if factoring == "expanded":
        rows = [r for r in product((OLD, DELTA), repeat=len(places)) if DELTA in r]
    else:
        before, after = {"old_prefix": (OLD, NEW), "new_prefix": (NEW, OLD)}[factoring]
        rows = [[before] * k + [DELTA] + [after] * (len(places) - k - 1) for k in range(len(places))]
    out = []
    for row in rows:
        tags = dict(zip(places, row, strict=True))
        out.append(tuple(lit.with_tag(tags.get(k)) for k, lit in enumerate(conj)))
    return out


def prune_grid(grid: list[Conj], changed: set[tuple[str, bool]]) -> list[Conj]:
    """Rows whose delta literals all have changes."""
    return [row for row in grid if all(lit.symbol in changed for lit in row if lit.tag == DELTA)]


def absorbed(clause: Clause) -> Clause:
    """Without bodies that another body's literals are part of."""
    keep = [b for b in clause.bodies if not any(set(c) < set(b) for c in clause.bodies)]
    return Clause(clause.head, tuple(keep))


def choose_step(label: str, clause: Clause, trusted: Iterable[str], deleted: set[tuple[str, bool]], changed: set[tuple[str, bool]] | None = None, sizes: dict[tuple[str, bool], int] | None = None, delta: dict[tuple[str, bool], int] | None = None, policy: str = "paper") -> str:
    """"skip", "rebuild" or "incremental".

    Rebuild if the head is not trusted or a body literal, as (label, closed), has deletions; skip if nothing in the
    bodies changed. policy="cost" also rebuilds where a body literal grows by more than it held, the point from which
    joining the changes reads more than joining anew (sizes: rows of the old relations, delta: of the changes).
    """
    used = {lit.symbol for b in clause.bodies for lit in b} - {None}
    if label not in set(trusted):
        return "rebuild"
    if changed is not None and not used & changed and not used & deleted:
        return "skip"
    if used & deleted:
        return "rebuild"
    if policy == "cost" and sizes is not None and delta is not None and any(delta.get(s, 0) > sizes.get(s, 0) > 0 for s in used):
        return "rebuild"
    return "incremental"
