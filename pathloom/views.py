"""The benchmark views: ten over the dense commerce graph, ten over the sparse activity graph, and the worked examples."""

from __future__ import annotations

from .plans.rules import Program, complete, merged, parse_rules, program

RING = merged(
    complete(parse_rules("watched(X, Y) :- connected(X, Y), monitors+(Z, X), monitors+(Z, Y), accredited(Z, X).")),
    program({"guarded": "connected/watched+/connected", "vetted": "~accredited & guarded & transfer", "handoff": "transfer | vetted", "ring": "handoff+ & ~(handoff+)"}),
)
DETECTABLE = merged(RING, complete(parse_rules("detectable(X, Y) :- ring(X, Y), monitors(Z, X), monitors(Z, Y).")))
AUDIENCE = program({"endorses": "likes & advertises+", "exposed": "follows*/endorses", "clients": "exposed/~exposed", "audience": "clients | ~clients"})

#: Name to (graph, program, label).
VIEWS: dict[str, tuple[str, Program, str]] = {
    name: ("commerce" if name[0] == "d" else "activity", p, label)
    for name, (p, label) in {
        **{
            k: (program({k: path}), k)
            for k, path in {
                "d1": "cust_in/~supp_in",
                "d2": "placed_F_1/contains_RF",
                "d3": "placed_O_2/sourced_NO | placed_P_2/sourced_NF",
                "d4": "(deals_BUILDING/supplies_1997) & wants_1",
                "d5": "transfer+",
                "d6": "connected*/cust_in",
                "d8": "wants_5/brand_7 | wants_5/brand_8",
                "d9": "~placed_F_1/connected+",
                "s3": "relay_click+",
                "s4": "(relay_view | relay_signup)+",
                "s5": "doc_copy+/doc_source",
                "s7": "~page_host/page_link",
                "s8": "said_system/turn_next+",
                "s9": "vec_next+/vec_class",
                "s10": "(touch_error/~touch_error) & relay_error+",
            }.items()
        },
        "d7": (RING, "ring"),
        "d10": (complete(parse_rules("d10(S, P) :- supplies_1995(S, P), sourced_AF(O, S), contains_AF(O, P).")), "d10"),
        "s1": (AUDIENCE, "exposed"),
        "s2": (AUDIENCE, "audience"),
        "s6": (complete(parse_rules("s6(X, Y) :- doc_copy+(X, Y), doc_quality(X, Z), doc_quality(Y, Z).")), "s6"),
        "detectable": (DETECTABLE, "detectable"),
    }.items()
}
VIEWS |= {"guarded": ("commerce", RING, "guarded"), "vetted": ("commerce", RING, "vetted"), "exposed": ("activity", AUDIENCE, "exposed")}
DENSE = tuple(f"d{k}" for k in range(1, 11))
SPARSE = tuple(f"s{k}" for k in range(1, 11))
