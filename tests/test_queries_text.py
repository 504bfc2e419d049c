import pytest

from rdf_assist.operators.mapping import Graph
from rdf_assist.operators.session import Assistant
from rdf_assist.plans import compile as plan
from rdf_assist.plans.ir import Pattern, SelectQuery, Term, iri, lit, validate, var
from rdf_assist.plans.parse import QuerySyntaxError, parse


@pytest.fixture(scope="module")
def star(spark, tiny):
    return Graph(spark, tiny, ("geo", "sales", "catalog"), False)


def test_parse_forms():
    q = parse('PREFIX ex: <http://x/> SELECT DISTINCT ?a (COUNT(DISTINCT ?b) AS ?n) WHERE { ?a ex:p ?b ; a <class/X> . ?b name "it\\"s"@en , "2"^^xsd:integer FILTER(?b >= 3 && ?b < 9.5) OPTIONAL { ?a q ?c } } GROUP BY ?a HAVING (COUNT(DISTINCT ?b) > 1) ORDER BY DESC(?n) ?a LIMIT 5 OFFSET 2')
    assert [str(p.p) for p in q.patterns] == ["http://x/p", "type", "name", "name"]
    assert q.patterns[2].o == Term("literal", 'it"s', "en") and q.patterns[3].o.dtype == "integer"
    assert (q.limit, q.offset, q.order_by, q.group_by) == (5, 2, (("n", True), ("a", False)), ("a",))
    assert q.having[0].variable == "n" and q.groups[0].kind == "optional" and len(q.filters) == 2
    assert parse("SELECT DISTINCT count(?c) WHERE { ?c p ?x }").aggregates[0].name == "count"
    assert parse("SELECT * WHERE { { ?a p ?b } UNION { ?a q ?b } MINUS { ?a r ?c } FILTER NOT EXISTS { ?a s ?d } }").groups[0].kind == "union"


@pytest.mark.parametrize("text", ["SELECT", "SELECT ?x WHERE { ?x }", "SELECT ?x WHERE { ?x p ", "SELECT ?x WHERE { ?x ^ ?y }", "SELECT ?x WHERE { ?x zz:p ?y }", "SELECT ?x WHERE { ?x p ?y } LIMIT ?z FOO"])
def test_parse_errors(text):
    with pytest.raises((QuerySyntaxError, ValueError)):
        parse(text)


def test_validate():
    assert validate(SelectQuery(())) == ["the query has no pattern"]
    q = SelectQuery((Pattern(lit("x"), iri("name"), var("y")),), ("z",))
    assert len(validate(q)) == 2
    assert validate(parse("SELECT ?x WHERE { ?x name ?y }")) == []


def test_answers_are_a_join(star):
    got = plan.run(star, parse('SELECT ?r WHERE { ?n name "NATION_3" ; region ?x . ?x name ?r }')).collect()
    n = star.table("nation").where("n_name = 'NATION_3'").first().n_regionkey
    assert [r.r for r in got] == [star.table("region").where(f"r_regionkey = {n}").first().r_name]


def test_predicate_variable_and_unknown_predicate(star):
    got = {(r.p, r.o) for r in plan.run(star, SelectQuery((Pattern(iri("region/1"), var("p"), var("o")),))).select("p", "o").collect()}
    assert got == {("type", "class/Region"), ("name", star.table("region").where("r_regionkey = 1").first().r_name)}
    assert plan.run(star, parse("SELECT ?x WHERE { ?x nothing ?y }")).count() == 0
    assert plan.run(star, parse("SELECT ?x WHERE { ?x name ?x }")).count() == 0


def test_hidden_columns_and_edits(star):
    q = parse('SELECT ?c ?n WHERE { ?c marketSegment "BUILDING" ; name ?n }')
    assert plan.run(star, SelectQuery(q.patterns, q.variables, hide=("c",))).columns == ["n"]
    other = q.with_term(0, "o", lit("MACHINERY"))
    assert plan.run(star, other).count() == star.table("customer").where("c_mktsegment = 'MACHINERY'").count()


def test_plan_scans_only_what_a_pattern_needs(star):
    text = plan.run(star, parse('SELECT ?c WHERE { ?c marketSegment "MACHINERY" }'))._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(c_mktsegment), EqualTo(c_mktsegment,MACHINERY)]" in text
    assert "c_acctbal" not in text and "CartesianProduct" not in text


def test_session_loop(spark, star):
    from rdf_assist.operators.index import build_cache

    a = Assistant(spark, star, build_cache(star, 50))
    assert a.run('SELECT ?c WHERE { ?c marketSegment "MACHINARY" }').count() == 0
    found = a.suggest().where("new = 'MACHINERY'").first()
    assert "MACHINERY" in found.text and found.n_answers == star.table("customer").where("c_mktsegment = 'MACHINERY'").count()
    assert a.prefetch().where(f"alt_id = {found.alt_id}").count() == found.n_answers
    assert a.accept(found.alt_id).count() == found.n_answers
    assert a.query.patterns[0].o.value == "MACHINERY"
    assert a.edit(0, o=lit("BUILDING")).count() == star.table("customer").where("c_mktsegment = 'BUILDING'").count()
    assert a.problems("SELECT ?z WHERE { ?c p ?y }")
    with pytest.raises(KeyError):
        a.run('SELECT ?c WHERE { ?c marketSegment "MACHINARY" }')
        a.suggest(structure=False)
        a.accept(99_999)
