"""Programs as ANSI SQL: a common table expression for each label and closure, for any engine with recursive CTEs."""

from __future__ import annotations

from .rules import Conj, Const, Eq, Program, Rel, Var, slice_labels, stratify


def body_sql(conj: Conj, head: tuple[Var, Var], name) -> str:
    tables, where, place = [], [], {}
    for lit in conj:
        if isinstance(lit.atom, Rel):
            t = f"t{len(tables)}"
            tables.append(f"{name(lit.atom.label, lit.closed)} AS {t}")
            for term, column in ((lit.atom.a, f"{t}.src"), (lit.atom.b, f"{t}.dst")):
                if isinstance(term, Const):
                    where.append(f"{column} = {term.id}")
                elif term.name in place:
                    where.append(f"{column} = {place[term.name]}")
                else:
                    place[term.name] = column
    todo = [lit.atom for lit in conj if isinstance(lit.atom, Eq)]
    while todo:
        for e in todo:
            ends = [str(t.id) if isinstance(t, Const) else place.get(t.name) for t in e.terms]
            if all(ends):
                where.append(f"{ends[0]} = {ends[1]}")
            elif any(ends):
                free, known = (e.b, ends[0]) if ends[0] else (e.a, ends[1])
                place[free.name] = known
            else:
                continue
            todo.remove(e)
            break
        else:
            tables.append(f"nodes AS t{len(tables)}")
            place[todo[0].a.name] = f"t{len(tables) - 1}.id"
    for v in head:
        if v.name not in place:
            tables.append(f"nodes AS t{len(tables)}")
            place[v.name] = f"t{len(tables) - 1}.id"
    return f"SELECT DISTINCT {place[head[0].name]} AS src, {place[head[1].name]} AS dst" + (f" FROM {', '.join(tables)}" if tables else "") + (f" WHERE {' AND '.join(where)}" if where else "")


def program_ctes(p: Program, view: str, base: dict[str, str], nodes: str | None = None) -> str:
    """The common table expressions up to a view's label; base: SQL of base labels; nodes: SQL of the node domain (id).

    Without `nodes`, the domain is that of the base labels in the view's slice.
    """
    keep = slice_labels(p, view)
    closed = p.closed_labels()
    ctes = []
    name = lambda label, plus: f"r_{label}_plus" if plus else f"r_{label}"

    def add(label: str, text: str) -> None:
        ctes.append(f"{name(label, False)} AS ({text})")
        if label in closed:
            n = name(label, False)
            ctes.append(f"{n}_plus AS (SELECT src, dst FROM {n} UNION SELECT p.src, e.dst FROM {n}_plus AS p, {n} AS e WHERE p.dst = e.src)")

    for label in sorted(keep & set(base) - set(p.clauses)):
        add(label, f"SELECT DISTINCT src, dst FROM ({base[label]}) AS q")
    domain = nodes or " UNION ".join(f"SELECT {c} AS id FROM {name(x, False)}" for x in sorted(keep & set(base) - set(p.clauses)) for c in ("src", "dst"))
    ctes.append(f"nodes AS ({domain})")
    for label in (x for x in stratify(p) if x in keep):
        add(label, " UNION ".join(body_sql(b, p.clauses[label].head, name) for b in p.clauses[label].bodies))
    return "WITH RECURSIVE " + ",\n".join(ctes)


def program_sql(p: Program, view: str, base: dict[str, str], nodes: str | None = None) -> str:
    return f"{program_ctes(p, view, base, nodes)}\nSELECT src, dst FROM r_{view}"
