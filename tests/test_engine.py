"""Numbering, shapes, facts, goals and answers on small trees, held against the brute force of treefacts.oracle."""

import random
from functools import reduce
from operator import mul

import pytest
from fixtures import HARBOUR, PAIR, PATHS

from treefacts import model
from treefacts.functions import keys
from treefacts.operators import evaluate
from treefacts.operators.answers import branch
from treefacts.operators.store import Store, positions
from treefacts.oracle import Reference, below, tree
from treefacts.plans import path as paths
from treefacts.plans import specialise
from treefacts.sources import markup


def dotted(okey):
    return ".".join(map(str, keys.decode(okey)))


def every(root):
    """All nodes of a brute-force tree: elements, texts and attributes."""
    return [n for x in (root, *below(root)) for n in (x, *x.attributes)]


@pytest.fixture(scope="module")
def stores(spark):
    out = {}
    for name, text in {"harbour": HARBOUR, "pair": PAIR}.items():
        nodes = markup.from_xml_text(spark.createDataFrame([(1, text)], "doc_id long, xml string")).cache()
        out[name] = Store.from_nodes(nodes)
        out[name].facts.cache()
    return out


def answers(store, path, **options):
    return sorted((dotted(r.okey), r.tag) for r in evaluate.query(store, path, **options).collect())


@pytest.mark.parametrize(("name", "text"), [("harbour", HARBOUR), ("pair", PAIR)])
def test_facts_and_positions(stores, name, text):
    """Every leaf, text and attribute is a fact of its record; positions go by record in document order."""
    want = {}
    for n in every(tree(markup.parse_xml(text))):
        if n.kind != "inner":
            record = n.parent
            want[(".".join(map(str, n.number)), n.tag)] = (n.value, ".".join(map(str, record.number)))
    placed = positions(stores[name].facts).orderBy("pos").collect()
    assert {(dotted(r.okey), r.pred): (r.value, dotted(r.gkey)) for r in placed} == want
    assert [r.pos for r in placed] == list(range(len(want)))
    first = {}
    for r in placed:
        assert r.gpos == first.setdefault(r.gkey, r.pos)
    assert [r.gkey for r in placed] == sorted(r.gkey for r in placed)


def test_rules(stores):
    """One rule for each distinct structure; records of one tag and level that differ get different types below."""
    rules = stores["pair"].rules
    assert [(tag, children, atts) for tag, _, children, atts, _ in rules.distinct()] == [("yard", ("lot",), ()), ("lot", ("item", "size"), ("k",)), ("lot", ("item",), ("k",))]
    lots = [s for s in rules.shapes if s.tag == "lot"]
    assert len({s.typ for s in lots}) == 1 and len({s.child_typ for s in lots}) == 2
    shapes = {}
    for n in every(tree(markup.parse_xml(HARBOUR))):
        if n.kind == "inner":
            shapes.setdefault(n.tag, set()).add((tuple(sorted({c.tag for c in n.children})), tuple(sorted(a.tag[1:] for a in n.attributes))))
    harbour = stores["harbour"].rules
    assert {tag: set(harbour.patterns(tag)) for tag in shapes} == shapes


@pytest.mark.parametrize("options", [{}, {"engine": "bottomup"}, {"order": "document"}, {"order": "cost"}])
def test_features_agree_with_brute_force(stores, options):
    reference = Reference(markup.parse_xml(HARBOUR))
    for path in PATHS:
        want = reference.query(path)
        assert want, path
        assert answers(stores["harbour"], path, **options) == want, path


def test_unification_of_two_constants(stores):
    path = '/yard/lot[item="oak" and item="elm"]/size'
    assert answers(stores["pair"], path) == Reference(markup.parse_xml(PAIR)).query(path) != []
    assert answers(stores["pair"], path, conjunction="unify") == []


def test_goals(stores):
    goal = lambda text: specialise.goals(stores["pair"].rules, paths.parse(text))
    assert {(g.tag, g.pattern) for g in goal('/yard/lot[item="ash"]/item')} == {("lot", (("item", "ash"),))}
    assert len(goal('/yard/lot[size=3]/item')) == 1  # only one of the two structures has a size
    assert {g.tag for g in goal("/yard/lot/item")} == {"item"}
    assert {g.pattern for g in goal('/yard/lot[@k=4 or size=12]/item')} == {(("@k", 4.0),), (("size", 12.0),)}


def test_derivations(stores):
    """As many ways as the product, over the tags of a record, of how many children have it."""
    def ways(x):
        by_tag = {}
        for c in x.children:
            by_tag.setdefault(c.tag, []).append(ways(c) if c.kind == "inner" else 1)
        return reduce(mul, (sum(v) for v in by_tag.values()), 1)

    want = {".".join(map(str, x.number)): ways(x) for x in tree(markup.parse_xml(PAIR)).children}
    got = {dotted(r.okey): r.n for r in evaluate.derivation_counts(stores["pair"], "/yard/lot").collect()}
    assert got == want and sum(want.values()) > len(want)


def test_specialised_rules_name_what_is_scanned(stores):
    """The predicates of the specialised rules are those that the plan reads, and records on the way."""
    for path in ('/yard/lot[size=12]/item', "/yard/lot/size"):
        tree_ = paths.parse(path)
        called = {p for r in specialise.rule_plan(stores["pair"].rules, tree_) for p in r.body}
        scanned = evaluate.scanned(stores["pair"], path)
        assert scanned <= called and called - scanned <= {"lot"}, path


def test_paths_render():
    for text in ('/a/b[c="x" and @d=2]/e', "/a//@*", "/a/(b|c)/..", "/a[not(b) and (c or d)]/text()", "/a[b/c>3]"):
        assert paths.render(paths.parse(text)) == text
    with pytest.raises(paths.PathError):
        paths.parse("/a/@b/c")


def random_tree(rng, budget=40):
    tags = "abcde"

    def make(depth):
        nonlocal budget
        budget -= 1
        atts = {t: str(rng.randint(1, 3)) for t in "xy" if rng.random() < 0.3}
        e = markup.Element(rng.choice(tags), atts)
        if depth == 0 or budget <= 0 or rng.random() < 0.2:
            e.children = [str(rng.randint(1, 3))]
            return e
        for _ in range(rng.randint(1, 4)):
            if rng.random() < 0.25 and (not e.children or not isinstance(e.children[-1], str)):
                e.children.append(rng.choice(["u", "v"]))
            elif budget > 0:
                e.children.append(make(depth - 1))
        e.children = e.children or ["u"]
        return e

    root = markup.Element("r", {})
    root.children = [make(4) for _ in range(3)]
    return root


def random_path(rng):
    def name():
        return rng.choice(["a", "b", "c", "d", "e", "*", "(a|b)"])

    def test():
        t = rng.choice(["@x", "@y", rng.choice("abcde"), f"{rng.choice('abcde')}/{rng.choice('abcde')}"])
        return t + rng.choice(["", "", "=1", "=2", ">1", '="1"'])

    out = "/r"
    for _ in range(rng.randint(1, 3)):
        out += rng.choice(["/", "/", "//"]) + name()
        if rng.random() < 0.4:
            out += f"[{test()}" + (rng.choice([" and ", " or "]) + test() if rng.random() < 0.4 else "") + "]"
    return out + rng.choice(["", "", "/@x", "/text()", "/..", "//@*"])


def test_random_trees(spark):
    rng = random.Random(7)
    roots = {i: random_tree(rng) for i in range(1, 7)}
    rows = [r for i, root in roots.items() for r in markup.rows_of(i, root)]
    store = Store.from_nodes(spark.createDataFrame(rows, model.NODES).cache())
    store.facts.cache()
    for _ in range(25):
        path = random_path(rng)
        want = sorted((i, *x) for i, root in roots.items() for x in Reference(root).query(path))
        got = sorted((r.doc_id, ".".join(map(str, keys.decode(r.okey))), r.tag) for r in evaluate.query(store, path).collect())
        assert got == want, path


def test_branch_is_the_subtree_of_the_definition(spark):
    """Correctness: what the engine keeps of random trees is the subtree that the definition gives, elements and facts alike."""
    rng = random.Random(11)
    roots = {i: random_tree(rng, 14) for i in range(1, 6)}
    rows = [r for i, root in roots.items() for r in markup.rows_of(i, root)]
    store = Store.from_nodes(spark.createDataFrame(rows, model.NODES).cache())
    store.facts.cache()
    some = 0
    for _ in range(12):
        path = random_path(rng)
        if path.endswith("/.."):
            path = path[:-3]
        want = {(i, *x) for i, root in roots.items() for x in Reference(root).subtree(path)}
        got = {(r.doc_id, dotted(r.okey), r.tag, r.kind) for r in branch(store, path, keep_attributes=True).collect()}
        assert {x for x in got if x[3] == "inner"} == {x for x in want if x[3] == "inner"}, path
        assert {x for x in got if x[3] != "inner"} == {x for x in want if x[3] != "inner"}, path
        some += bool(want)
        free = paths.render(specialise.existence_form(paths.parse(path)))
        every_ = {(r.doc_id, dotted(r.okey), r.tag) for r in evaluate.query(store, free).collect()}
        assert {(r.doc_id, dotted(r.okey), r.tag) for r in evaluate.query(store, path).collect()} <= every_, path
    assert some >= 4


@pytest.mark.parametrize("options", [{"value_test": "own_text"}, {"value_test": "string_value"}, {"text_mode": "strict"}])
def test_other_readings_agree_with_brute_force(stores, options):
    reference = Reference(markup.parse_xml(HARBOUR), **options)
    for path in ('/port/day[berth="closed for "]/tide', '//berth[ship="Brisk"]/crew', "//berth/text()", "//note//text()", '//day[note="no traffic"]', '//ship[tow="AlvaDart"]/name'):
        assert answers(stores["harbour"], path, **options) == reference.query(path), path


def test_type_scope_may_let_others_in(stores):
    exact, literal = (set(answers(stores["harbour"], "/port/day/berth", **o)) for o in ({}, {"goal_scope": "type"}))
    assert exact <= literal


def test_literal_and_unique_types(spark, stores):
    from treefacts.operators import shapes

    found = stores["harbour"].rules.shapes
    unique = shapes.type_numbers(found, "unique")
    assert len({s.typ for s in unique}) == len(unique)
    nodes = markup.from_xml_text(spark.createDataFrame([(1, HARBOUR)], "doc_id long, xml string"))
    literal = {dotted(r.okey): r.n for r in shapes.literal_types(nodes).collect()}
    inner = [n for n in every(tree(markup.parse_xml(HARBOUR))) if n.kind == "inner"]
    sig = lambda n: (n.tag, tuple(sorted({c.tag for c in n.children})), tuple(sorted(a.tag for a in n.attributes)))
    for n in inner:
        before = [m for m in inner if len(m.number) == len(n.number) and m.number < n.number and m.tag == n.tag]
        assert literal[".".join(map(str, n.number))] == sum(sig(m) != sig(n) for m in before)
    deep = {dotted(r.okey): r.deep for r in shapes.deep_signatures(nodes).collect()}

    def whole(n):
        return sig(n), frozenset(whole(c) for c in n.children if c.kind == "inner")

    for n in inner:
        for m in inner:
            a, b = (deep[".".join(map(str, x.number))] for x in (n, m))
            assert (a == b) == (whole(n) == whole(m))
    assert shapes.relation(("a", (), ()), ("b", (), ())) == "distinct"
