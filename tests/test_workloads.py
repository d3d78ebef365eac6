"""Queries against their SQL on the smallest tables, plans, round trips, and what is left without the training-data folders."""

import glob
import math
from pathlib import Path

import duckdb
import pytest

from treefacts import collections as trees
from treefacts import workloads
from treefacts.operators import answers, evaluate, index, rebuild
from treefacts.operators.store import Store
from treefacts.sources import markup

NAMES = ["w01_two_attributes_any_child", "w06_wildcard_inside", "w08_up_two", "w11_alternatives_twice", "w12_alternatives_at_end", "w16b_below_any_child", "w21_selective_equality", "w27_attribute_and_leaf", "w28_attribute_or_leaf", "w31_two_shapes", "m_unspecialised", "m_branch", "m_forest", "m_index", "m_derivations", "m_rules", "m_access_counts", "op_asof", "op_range_join", "op_cube", "op_rank", "st_tumbling", "st_late", "st_shapes"]


def shown(v):
    return ("nan" if math.isnan(v) else round(v, 6)) if isinstance(v, float) else v


@pytest.fixture(scope="module")
def db(tiny):
    con = duckdb.connect()
    for p in glob.glob(f"{tiny}/*.parquet"):
        con.execute(f"create view {Path(p).stem} as select * from '{p}'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_equals_sql(spark, tiny, db, name):
    df = workloads.QUERIES[name](spark, tiny)
    columns = sorted(df.columns)
    got = sorted((tuple(shown(r[c]) for c in columns) for r in df.collect()), key=str)
    found = db.execute(workloads.SQL[name])
    names = [d[0] for d in found.description]
    assert sorted(names) == columns
    assert got == sorted((tuple(shown(row[names.index(c)]) for c in columns) for row in found.fetchall()), key=str)


def test_plans_prune_and_push(spark, tiny):
    df = evaluate.query(trees.store(spark, tiny, "K3"), "/parts/part[size=10]/name")
    plan = df._jdf.queryExecution().toString()
    assert "PartitionFilters" in plan and "PushedFilters" in plan
    assert "CartesianProduct" not in plan and "BatchEvalPython" not in plan and "BroadcastNestedLoopJoin" not in plan


def test_round_trip_of_text(spark):
    text = '<a x="1&quot;"><b>one &amp; two</b>run<c><d></d></c></a>'
    store = Store.from_nodes(markup.from_xml_text(spark.createDataFrame([(1, text)], "doc_id long, xml string")))
    made = rebuild.document(store).first().xml
    assert made == text
    again = Store.from_nodes(markup.from_xml_text(spark.createDataFrame([(1, made)], "doc_id long, xml string")))
    assert sorted(map(tuple, again.facts.select("pred", "value", "okey").collect())) == sorted(map(tuple, store.facts.select("pred", "value", "okey").collect()))


def test_trace(spark):
    """Accesses in order: the first index steps through the first test's predicate, the second through what the hits' groups hold."""
    from fixtures import PAIR

    from treefacts.operators.store import positions

    store = Store.from_nodes(markup.from_xml_text(spark.createDataFrame([(1, PAIR)], "doc_id long, xml string")))
    facts = positions(store.facts).orderBy("pos").collect()
    log = [(a.index, a.pred, a.pos, a.hit) for a in index.trace(store, '/yard/lot[@k=7 and item="elm"]/size')]
    want = []
    for f in facts:
        if f.pred != "@k":
            continue
        want.append(("first", "@k", f.pos, f.value == "7"))
        if f.value != "7":
            continue
        group = [g for g in facts if g.gpos == f.gpos]
        for g in (g for g in group if g.pred == "item"):
            want.append(("second", "item", g.pos, g.value == "elm"))
            if g.value == "elm":
                want += [("second", "size", x.pos, True) for x in group if x.pred == "size"]
                break
    assert log == want and {hit for _, _, _, hit in log} == {True, False}


def test_files_of_records(spark, tmp_path):
    (tmp_path / "big.xml").write_text("<list>" + "".join(f"<row k='{i}'><v>{i * i}</v></row>\n" for i in range(50)) + "</list>")
    store = Store.from_nodes(markup.from_xml_file(spark, str(tmp_path / "big.xml"), "row", "list").cache())
    assert [r.value for r in evaluate.query(store, "/list/row[@k=7]/v").collect()] == ["49"]
    assert evaluate.query(store, "//row").count() == 50


def test_plans_without_tests_that_the_structure_tells(spark, tiny):
    store = trees.store(spark, tiny, "K1")
    for path in ("/orders/order[@status and @priority]/*", "/orders/order[item]/orderkey", "/orders/order[not(item)]/orderkey"):
        assert "Join" not in evaluate.query(store, path)._jdf.queryExecution().optimizedPlan().toString(), path
    plan = evaluate.query(store, '/orders/order[@status and custkey=85]/total')._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == 1 and "@status" not in plan


def test_several_appends(spark, tmp_path):
    texts = ["<r><a>1</a></r>", "<r><b>2</b></r>", "<r><c><d>3</d></c></r>", "<r><a>4</a></r>"]
    nodes = lambda i: markup.from_xml_text(spark.createDataFrame([(i, texts[i])], "doc_id long, xml string"))
    path = str(tmp_path / "s")
    store = Store.from_nodes(nodes(0))
    store.write(path)
    for i in (1, 2, 3):
        store.append(nodes(i), path)
    every = Store.open(spark, path)
    assert [(x, [r.value for r in evaluate.query(every, x).orderBy("doc_id").collect()]) for x in ("/r/a", "/r/b", "/r/c/d")] == [("/r/a", ["1", "4"]), ("/r/b", ["2"]), ("/r/c/d", ["3"])]
    assert len({s.child_typ for s in every.rules.shapes if s.tag == "r"}) == 3  # three structures of one tag
    # a batch without its rules isn't seen
    every.facts.write.parquet(f"{path}/facts/batch=9/pred=x")
    assert Store.open(spark, path).facts.count() == 4


def test_facts_are_spread_over_tasks(spark):
    texts = [(i, "<r><p><q>1</q></p></r>") for i in range(400)]
    facts = Store.from_nodes(markup.from_xml_text(spark.createDataFrame(texts, "doc_id long, xml string"))).facts
    from treefacts.functions import keys
    from treefacts.operators.store import SIBLINGS
    from pyspark.sql import functions as F

    parts = facts.repartition(32, "pred", "doc_id", keys.cut(F.col("gkey"), 2), F.substring("gkey", 2 * keys.WIDTH + 1, keys.WIDTH - SIBLINGS)).groupBy(F.spark_partition_id()).count().collect()
    assert len(parts) > 20 and max(r["count"] for r in parts) < 60


def test_append_and_exists(spark, tmp_path):
    one, two = ("<r><a>1</a></r>", "<r><b>2</b></r>")
    nodes = lambda i, x: markup.from_xml_text(spark.createDataFrame([(i, x)], "doc_id long, xml string"))
    store = Store.from_nodes(nodes(1, one))
    store.write(str(tmp_path / "s"))
    store.append(nodes(2, two), str(tmp_path / "s"))
    both = Store.open(spark, str(tmp_path / "s"))
    assert answers.exists(both, "/r/b") and answers.exists(both, "/r/a") and not answers.exists(both, "/r/c")


def test_imports_without_the_training_data_folders():
    for p in Path(workloads.__file__).parent.rglob("*.py"):
        if "llm" not in p.parts:
            assert "treefacts.llm" not in p.read_text()


def test_derivation_rows_are_not_capped(spark, tiny):
    text = "<r>" + "<v><a>1</a><a>2</a></v>" * 600 + "</r>"
    store = Store.from_nodes(markup.from_xml_text(spark.createDataFrame([(1, text)], "doc_id long, xml string")))
    assert evaluate.derivations(store, "/r/v").count() == 1200
    assert evaluate.derivations(store, "/r/v", limit=7).count() == 7
    assert "Limit" not in workloads.QUERIES["w22_derivation_rows"](spark, tiny)._jdf.queryExecution().toString()


def test_titles_equal_sql(spark, tmp_path):
    html = ["<title>Say &quot;a</title><p>x</p>", "<html><head><title> two words </title></head><svg><title>inner</title></svg></html>", "<p>none</p>", None, "<html><title></title></html>", "<html><title>a &amp; b</title></html>"]
    spark.createDataFrame(list(enumerate(html)), "page_id long, html string").write.parquet(str(tmp_path / "pages.parquet"))
    con = duckdb.connect()
    con.execute(f"create view pages as select * from '{tmp_path}/pages.parquet/*.parquet'")
    want = con.execute(workloads.SQL["page_titles"]).fetchall()
    assert sorted(tuple(r) for r in workloads.QUERIES["page_titles"](spark, str(tmp_path)).select("doc_id", "title").collect()) == sorted(want) == [(1, "two words")]


@pytest.mark.parametrize("name", ["m_types", "m_goals", "m_rule_plan", "m_existence_form", "m_unify"])
def test_methods_read_a_table(spark, tiny, db, monkeypatch, name):
    """Also when the session has translated it before."""
    if name == "m_unify":
        assert workloads.QUERIES[name](spark, tiny).inputFiles()
    else:
        monkeypatch.setattr(trees, "store", None)
    got = [r.asDict() for r in workloads.QUERIES[name](spark, tiny).collect()]
    assert got
    if name in workloads.SQL:
        found = db.execute(workloads.SQL[name])
        names = [c[0] for c in found.description]
        want = [dict(zip(names, row, strict=True)) for row in found.fetchall()]
        shown_rows = lambda rows: sorted(tuple((k, shown(v)) for k, v in sorted(r.items())) for r in rows)
        assert shown_rows(got) == shown_rows(want)


def test_written_levels_hold_no_column_of_the_table_twice(spark, tiny, monkeypatch):
    from treefacts.sources import publish

    seen, materialise = [], publish.materialise
    monkeypatch.setattr(publish, "materialise", lambda df, name="table": seen.append((name, df.columns)) or materialise(df, name))
    trees.orders_tree(spark, tiny)
    assert [name for name, _ in seen] == ["ranked", "level", "level"]
    assert not [c for name, columns in seen for c in columns if name == "level" and c[:2] in ("o_", "l_") and c != "o_orderkey"]
    assert "_inner" not in seen[0][1]
