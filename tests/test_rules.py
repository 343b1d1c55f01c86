import pytest

from pathloom.plans.rules import DELTA, NEW, OLD, Const, Eq, Lit, Program, Rel, RuleError, Var, ViewQuery, absorbed, check_safe, choose_step, complete, is_slice, is_stratified, is_uc2rpq, mask_grid, parse_path, parse_rules, program, prune_grid, slice_for, stratify

X, Y = Var("X"), Var("Y")


def test_completion_makes_one_clause():
    p = complete(parse_rules("p(1, 2). p(A, B) :- q(A, C), r+(C, B)."))
    assert set(p.clauses) == {"p"}
    fact, rule = p.clauses["p"].bodies
    assert {lit.atom for lit in fact} == {Eq(X, Const(1)), Eq(Y, Const(2))}
    assert rule[0].atom.a == X and rule[1].atom.b == Y and rule[1].closed and rule[0].atom.b == rule[1].atom.a


def test_repeated_head_variable_becomes_an_equality():
    body = complete(parse_rules("p(A, A) :- q(A, A).")).clauses["p"].bodies[0]
    assert Lit(Eq(Y, X)) in body and body[0].atom == Rel("q", X, X)


def test_sugar():
    p = program({"v": "~a*/b"})
    assert len(p.clauses["v"].bodies) == 2
    assert program({"v": "(a | b)+"}).clauses["v_aux1"].bodies[1][0].atom.label == "b"
    assert not Lit(Eq(X, Y), True).closed


def test_safety_by_body():
    p = complete(parse_rules("p(A, B) :- q(A, A). p(A, B) :- q(A, B)."))
    assert check_safe(p) == [("p", 0, "Y")]
    assert check_safe(p, strict=False) == []


def test_order_and_slices():
    p = program({"a": "b/c", "b": "d+", "e": "a & b"})
    assert stratify(p).index("b") < stratify(p).index("a") < stratify(p).index("e")
    assert is_stratified(p, {"c", "d"}, ["b", "a", "e"]) and not is_stratified(p, {"c", "d"}, ["a", "b"])
    assert is_slice(p, {"b", "d"}) and not is_slice(p, {"a", "c"})
    assert set(slice_for(ViewQuery(p, "a")).program.clauses) == {"a", "b"}
    assert is_uc2rpq(ViewQuery(p, "e"))


@pytest.mark.parametrize("paths", [{"a": "a/b"}, {"a": "b/c", "b": "a+"}])
def test_recursion_is_rejected(paths):
    with pytest.raises(RuleError, match="recursive"):
        stratify(program(paths))


@pytest.mark.parametrize("text", ["a(X Y) :- b(X, Y).", "a(X, Y) :- 3.", "~a(X, Y) :- b(X, Y)."])
def test_bad_rules(text):
    with pytest.raises(RuleError):
        parse_rules(text)


@pytest.mark.parametrize("text", ["a/", "(a", "a b", "&a"])
def test_bad_paths(text):
    with pytest.raises(RuleError):
        parse_path(text)


def test_mask_grids():
    body = program({"v": "a/b/c"}).clauses["v"].bodies[0]
    tags = lambda f: [[lit.tag for lit in r] for r in mask_grid(body, f)]
    assert tags("old_prefix") == [[DELTA, NEW, NEW], [OLD, DELTA, NEW], [OLD, OLD, DELTA]]
    assert tags("new_prefix") == [[DELTA, OLD, OLD], [NEW, DELTA, OLD], [NEW, NEW, DELTA]]
    assert len(tags("expanded")) == 7
    assert len(prune_grid(mask_grid(body), {("b", False)})) == 1


def test_steps_and_rewrites():
    c = program({"v": "a+/b"}).clauses["v"]
    assert choose_step("v", c, {"v"}, {("a", False)}, {("a", False)}) == "skip"  # only a+ is read
    assert choose_step("v", c, {"v"}, {("a", True)}, {("a", True)}) == "rebuild"
    assert choose_step("v", c, {"v"}, set(), {("b", False)}) == "incremental"
    assert choose_step("v", c, set(), set(), set()) == "rebuild"
    assert choose_step("v", c, {"v"}, set(), {("b", False)}, {("b", False): 3}, {("b", False): 9}, "cost") == "rebuild"
    assert len(absorbed(program({"v": "a | a & b"}).clauses["v"]).bodies) == 1
    assert Program().is_base("x")
