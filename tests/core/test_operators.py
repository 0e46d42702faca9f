"""Queries against independent SQL on the smallest tables, and operators on odd strings."""

import glob
import os
import random
from decimal import Decimal

import duckdb
import pytest
from pyspark.sql import functions as F

from seqschema.functions import expr, registry, solver
from seqschema.functions.solver import Summary
from seqschema.operators import learners as ln
from seqschema.operators import strings as st
from seqschema.operators import validate as va
from seqschema.plans import catalogue
from seqschema.sources import markup, planted, schemas
from seqschema.streaming import incremental

SF = "/root/testdata/sf0.001"
SOME = [
    "strings_roles", "strings_session", "distinct_flags", "length_hist_flags", "multiplicity_line_kind", "order_pairs_flags", "order_masks_flags", "conflicts_line_kind", "one_way_line_kind", "cooccurrence_flags",
    "never_together_line_kind", "components_roles", "automaton_line_kind", "contracted_sorted_flags", "levels_roles", "model_roles", "model_sorted_flags", "all_shuffle_flags", "universal_priority", "universal_size_flags",
    "coverage_line_kind", "model_example", "measures_example", "merge_equals_batch", "chunked_equals_whole", "stream_equals_batch", "planted_draws", "usage_proportions", "relaxng_round_trip", "tumbling_models",
    "usage_cube", "class_flags_examples", "validate_roles", "sliding_models",
    "coverage_fixed_models", "violations_fixed_model", "coverage_learners_roles", "chain_factor_sorted_flags", "compare_learners_roles", "published_xml_strings", "shape_measures", "automaton_example", "levels_example",
    "usage_learned", "alphabet_sweep", "model_published_xml", "strings_json_keys", "model_json_keys",
]


FROM_TABLES = [
    *(f"{x}_example" for x in catalogue.FROM_LINES), "model_example", "measures_example", "min_support_example", "class_flags_examples", "language_size_table6",
]


def plain(rows):
    return sorted([tuple(round(float(v), 6) if isinstance(v, float | Decimal) else v for v in r) for r in rows], key=repr)


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    got = catalogue.queries()[name](spark, SF)
    columns = sorted(got.columns)
    want = con.execute(f"SELECT {', '.join(columns)} FROM ({catalogue.oracle_sql()[name]})").fetchall()
    assert plain(tuple(r[c] for c in columns) for r in got.collect()) == plain(want)


@pytest.mark.parametrize("name", [x for x in FROM_TABLES if x not in SOME])
def test_example_equals_sql(spark, name):
    test_query_equals_sql(spark, name)


@pytest.mark.parametrize("name", FROM_TABLES)
def test_examples_read_a_given_table(spark, name):
    assert any(x.endswith((".parquet", ".parquet/")) or "summary-" in x or "conflicts-" in x or "components-" in x for x in catalogue.queries()[name](spark, SF).inputFiles())


def test_sample_of_four_strings(spark):
    s = st.summarise(catalogue._sample(spark))
    found = ln.learn(s, {"level_chain": {}, "outer_shuffle": {"mis": "exact"}, "disjunctive_bag": {}, "all_shuffle": {}})
    assert {r["learner"]: r["expr"] for r in found.collect()} == {"level_chain": "a* (b* c+ & d) (e & f?)", "outer_shuffle": "a* b* c+ e & d f?", "disjunctive_bag": "a* & b* & c+ & d & e & f?", "all_shuffle": "a* & b* & c+ & d & e & f?"}
    got = ln.measure(spark.createDataFrame([("example", "level", "a* (b* c+ & d) (e & f?)")], "model_key string, learner string, expr string"), s).first()
    assert (f"{got['ls']:.3e}", round(got["data_cost"], 4), int(got["shuffle_count"])) == ("4.862e+3", 85.6647, 6)


def strings(spark, seqs, key="m"):
    return spark.createDataFrame([(key, i, s) for i, s in enumerate(seqs)], "model_key string, string_id int, seq array<string>")


def test_summary_equals_plain_python(spark):
    rnd = random.Random(1)
    samples = {f"k{i}": ["".join(rnd.choice("abcd") for _ in range(rnd.randrange(6))) for _ in range(6)] for i in range(30)}
    df = spark.createDataFrame([(k, i, list(s)) for k, own in samples.items() for i, s in enumerate(own)], "model_key string, string_id int, seq array<string>")
    for name in solver.LEARNERS:
        got = {r["model_key"]: r["expr"] for r in ln.learn(st.summarise(df), [name]).collect()}
        want = {k: solver.LEARNERS[name](Summary.of(own))["expr"] for k, own in samples.items() if any(own)}
        assert got == want, name


def test_summary_by_arrays_equals_plain_counts(spark):
    rnd = random.Random(3)
    symbols = ["a", "1:b", "é", "x y", "", "⊢", "s3", "s4", "\U0001f600"]
    rows = [(f"k{i % 3}", [rnd.choice(symbols[: 3 + 3 * (i % 3)]) for _ in range(rnd.randrange(14))]) for i in range(400)] + [("void", []), (None, ["a", "b"])]
    want = {}
    for key, seq in {(k, tuple(s)) for k, s in rows}:
        w = rows.count((key, list(seq)))
        ahead = {(x, y) for i, x in enumerate(seq) for y in seq[i + 1 :] if x != y}
        facts = [("T", "", "", 0), ("L", str(len(seq)), "", 0), *(("S", x, "", seq.count(x)) for x in set(seq)), *(("P", *p, 0) for p in ahead)]
        for kind, a, b, hi in facts + [("E", *e, 0) for e in set(zip([solver.SOURCE, *seq], [*seq, solver.SINK], strict=True))]:
            n, v, most = want.get((key, kind, a, b), (0, 0, 0))
            want[key, kind, a, b] = n + 1, v + w, max(most, hi)
    s = spark.createDataFrame([(k, i, x) for i, (k, x) in enumerate(rows)], "model_key string, string_id int, seq array<string>").repartition(3)
    for got in (st.summarise(s), st.summarise_batches(st.distinct_strings(s))):
        found = got.select("model_key", "kind", "a", "b", "n", "w", "hi").collect()
        assert {tuple(r)[:4]: tuple(r)[4:] for r in found} == want and len(found) == len(want)
    assert st.summarise_batches(st.distinct_strings(s).limit(0)).count() == 0
    invalid = spark.sql("SELECT 'k' AS model_key, 1 AS string_id, array(CAST(X'E2' AS STRING), 'b', CAST(X'C3' AS STRING)) AS seq")
    ends = st.summarise(invalid).where("kind = 'E'").selectExpr("hex(a) AS a", "hex(b) AS b").collect()
    assert {tuple(r) for r in ends} == {("E28AA2", "E2"), ("E2", "62"), ("62", "C3"), ("C3", "E28AA3")}


def test_odd_strings(spark):
    s = strings(spark, [["a", None, "b"], [], ["x y", "é", "⊢"], None])
    assert st.dropped_symbols(s.where("seq IS NOT NULL")).first()["n"] == 1
    e = expr.parse_expr(ln.infer_level_chain(s.where("seq IS NOT NULL")).first()["expr"])
    assert set(expr.symbols(e)) >= {"a", "b", "x y", "é"}
    assert ln.infer_level_chain(strings(spark, [[]])).count() == 0 and ln.infer_level_chain(s.limit(0)).count() == 0
    names = [f"s{i:02d}" for i in range(70)]
    wide = strings(spark, [names, names[::-1]])
    masks = st.order_masks(st.distinct_strings(wide)).collect()
    assert sum(bin(r["mask"]).count("1") for r in masks) == 70 * 69
    assert ln.infer_level_chain(wide).first()["n_symbols"] == 70


def test_long_chains_of_components_and_levels(spark):
    names = [f"s{i:03d}" for i in range(130)]
    pairs = [("m", a, b) for x, y in zip(names[:40], names[1:40], strict=False) for a, b in ((x, y), (y, x))]
    symbols = spark.createDataFrame([("m", x) for x in names[:41]], "model_key string, sym string")
    got = {r["sym"]: r["comp"] for r in st.components(symbols, spark.createDataFrame(pairs, "model_key string, a string, b string")).collect()}
    assert got == {x: names[0] for x in names[:40]} | {names[40]: names[40]}
    path = [solver.SOURCE, *names, solver.SINK]
    edges = spark.createDataFrame([("m", a, b) for a, b in zip(path, path[1:], strict=False)] + [("m", names[3], names[5])], "model_key string, src string, dst string")
    rows = st.levels(edges).collect()
    assert {r["node"]: r["level"] for r in rows} == {x: i for i, x in enumerate(path)} and [r["node"] for r in rows if r["skip"]] == [names[4]]


def test_validation_agrees_with_derivatives(spark):
    rnd = random.Random(2)
    train = strings(spark, [list(s) for s in ("aabcde", "acdcfe", "dbbcfe", "adbcef")])
    tests = [[rnd.choice("abcdefg") for _ in range(rnd.randrange(9))] for _ in range(300)] + [list("abcdef"), list("dbcef"), list("abcdf")]
    model = ln.infer_level_chain(train)
    e = expr.parse_expr(model.first()["expr"])
    for r in va.validate(strings(spark, tests), model).collect():
        assert r["ok"] == expr.matches_general(r["seq"], e), r
    kinds = {r["reason"] for r in va.validate(strings(spark, [["g"], ["a"], list("bcdefa"), list("bcde")]), model).collect()}
    assert kinds == {"unknown", "count", "order", None}
    assert va.validate(strings(spark, [["a"]], "other"), model).first()["reason"] == "no model"


def test_validation_of_every_learner_agrees_with_derivatives(spark):
    rnd = random.Random(17)
    seqs = [[rnd.choice("abcd") for _ in range(rnd.randrange(5))] for _ in range(60)]
    s = strings(spark, seqs)
    models = ln.learn(st.summarise(s.where("string_id < 4")), [*solver.LEARNERS])
    texts = {r["learner"]: r["expr"] for r in models.collect()}
    got = va.validate(s, models).collect()
    assert len(got) == len(seqs) * len(texts) == 60 * 7
    for r in got:
        assert r["ok"] == (r["reason"] is None) == expr.matches_general(r["seq"], expr.parse_expr(texts[r["learner"]])), r
    assert {r["reason"] for r in got} >= {None, "unknown", "no match"} or {r["reason"] for r in got} >= {None, "no match"}
    one = ln.learn(st.summarise(strings(spark, [["a", "b"], ["c", "d"]])), {"level_chain": {"same_level": "choice"}})
    assert [r["coverage"] for r in va.coverage(strings(spark, [["a", "b"], ["c", "d"]]), one).collect()] == [1.0]


def test_planted_sizes_are_shares(spark):
    keys = spark.range(5000).withColumnRenamed("id", "k")
    got = {r["model_key"]: r["count"] for r in planted.planted_strings(keys, "k", sizes=planted.SIZES, least=100).groupBy("model_key").count().collect()}
    assert got["web"] == 5000 and abs(got["doc"] - 4300) < 150 and 50 < got["astro"] < 160 and 90 < got["thesis"] < 240


def test_markup_strings_are_counted_as_they_are_read(spark):
    texts = ["<a><b/><c><b/></c><b/></a>"] * 300 + ["<a>", "", None, "<ul><li>1<li>2<p>x</ul>", "<a><b/></a>"]
    docs = spark.createDataFrame([(x,) for x in texts], "t string").coalesce(1)
    for options in ({}, {"context": 1}, {"mode": "html"}, {"mode": "html", "implied_end": False}):
        want = st.distinct_strings(markup.strings_from_markup(docs, "t", **options)).collect()
        found = markup.distinct_from_markup(docs, "t", **options, most=20)
        assert sorted((r["model_key"], r["seq"], r["n"]) for r in found.collect()) == sorted((r["model_key"], r["seq"], r["n"]) for r in want), options
        assert "array<struct<tag" not in found._jdf.queryExecution().executedPlan().toString() and "MapInArrow" in found._jdf.queryExecution().executedPlan().toString()


def test_markup_modes():
    text = "<html><body><p><b>x<br><p>y</p><p>z</p><ul><li>1<li>2</ul></body></html>"
    nested = {t: s for t, s, _ in markup.html_elements(text, False) if t in ("b", "body")}
    assert nested["b"] == ["br", "p", "p", "ul"] and {t: s for t, s, _ in markup.html_elements(text)}["body"] == ["p", "p", "p", "ul"]
    assert markup.xml_elements("<a><b/><c><d/></c></a>")[0][:2] == ("a", ["b", "c"]) and markup.xml_elements("<a>") == []


def test_schema_readers():
    assert schemas.content_models("<!ELEMENT a (b, (c | d)*, e?)><!ELEMENT b (#PCDATA)>") == [("a", "b (c | d)* e?"), ("b", "()")]
    xsd = '<xs:schema xmlns:xs="http://www.w3.org/2001/XMLSchema"><xs:element name="r"><xs:complexType><xs:sequence><xs:element name="x" maxOccurs="unbounded"/><xs:all><xs:element name="y" minOccurs="0"/><xs:element name="z"/></xs:all></xs:sequence></xs:complexType></xs:element></xs:schema>'
    assert schemas.content_models(xsd) == [("r", "x+ (y? & z)")] and schemas.content_models("no schema") == []


def test_dtd_entities():
    dtd = """<!-- <!ELEMENT no (x)> --><!ENTITY % inline "b | %more;"><!ENTITY % more 'c'><!ENTITY % inline "z">
        <!ELEMENT a (t, (%inline;)*)><!ELEMENT COMPANY (MANY, b?)><!ELEMENT e EMPTY><!ELEMENT any ANY><!ELEMENT out (%external;)>"""
    found = dict(schemas.content_models(dtd))
    assert found == {"a": "t (b | c)*", "COMPANY": "MANY b?", "e": "()", "any": "(COMPANY | a | any | e | out)*"}
    assert schemas.content_models('<!ENTITY % x "%x;"><!ELEMENT a (%x;)><!ELEMENT b (c)>') == [("b", "c")]
    bomb = "".join(f'<!ENTITY % e{i} "{f"%e{i + 1};" * 50}">' for i in range(15)) + "<!ELEMENT a (%e0;)><!ELEMENT b (c)>"
    assert schemas.content_models(bomb) == [("b", "c")]


def test_xsd_groups_and_extensions():
    xsd = """<xs:schema xmlns:xs="http://www.w3.org/2001/XMLSchema" xmlns:t="urn:t"><xs:group name="g"><xs:choice><xs:element name="x"/><xs:element name="y"/></xs:choice></xs:group>
        <xs:complexType name="base"><xs:sequence><xs:element name="a"/><xs:element name="gone" minOccurs="0" maxOccurs="0"/></xs:sequence></xs:complexType>
        <xs:complexType name="more"><xs:complexContent><xs:extension base="t:base"><xs:sequence><xs:group ref="t:g" minOccurs="0" maxOccurs="unbounded"/></xs:sequence></xs:extension></xs:complexContent></xs:complexType>
        <xs:element name="r" type="t:more"/><xs:element name="s" type="xs:string"/><xs:element name="q"><xs:complexType><xs:sequence><xs:element ref="t:r"/><xs:group ref="t:none"/></xs:sequence></xs:complexType></xs:element>
        <xs:complexType name="own"><xs:complexContent><xs:extension base="t:own"><xs:sequence><xs:element name="z"/></xs:sequence></xs:extension></xs:complexContent></xs:complexType><xs:element name="o" type="t:own"/></xs:schema>"""
    assert [x for x in schemas.content_models(xsd) if x[0] in ("r", "s", "q", "o")] == [("r", "a (x | y)*"), ("q", "r"), ("o", "z")]


def test_sql_names(spark):
    registry.register(spark)
    r = spark.sql("SELECT expr_class('a & b').outer_shuffle AS o, shuffle_count('a b & c') AS s, expr_length('a* b') AS n, simplify('(a?)?') AS t, matches(array('a'), 'a?') AS m").first()
    assert tuple(r) == (True, 3.0, 4, "a?", True)
    assert [tuple(x) for x in spark.sql("SELECT w.* FROM VALUES ('a? & b') t(e), LATERAL word_counts(e) w ORDER BY 1").collect()][:3] == [(0, 0.0), (1, 1.0), (2, 2.0)]


def test_drift_and_versions(spark, tmp_path):
    old, new = (st.summarise(strings(spark, s), False) for s in ([["a", "b"]], [["b", "a"]]))
    assert [(r["a"], r["b"]) for r in incremental.new_conflicts(old, st.merge_summaries(old, new)).collect()] == [("a", "b")]
    seen = []
    merge = incremental.merge_batch(str(tmp_path), lambda models, n: seen.append((n, models.count())))
    for n, s in enumerate(([["a", "b"]], [["a", "b"]], [["b", "a"]])):
        merge(strings(spark, s), n)
        merge(strings(spark, s), n)  # a batch that runs again writes the same version
    assert incremental.latest(spark, str(tmp_path)).first()["expr"] == "a & b" and [x[1] for x in seen][::2] == [1, 0, 1]


def test_planted_draws_agree(spark):
    df = spark.range(50).select("id", planted.draw_column(F.col("id"), F.lit(3).cast("bigint")).alias("x"))
    assert all(r["x"] == planted.draw(r["id"], 3) for r in df.collect())


def test_statistics_run_in_the_jvm_with_one_exchange_after_distinct(spark):
    plan = st.summarise(catalogue.WORKLOADS["flags"](spark, SF), need_distinct=False)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Cartesian" not in plan and plan.count("Exchange hashpartitioning") == 2
