"""Work that the n-gram join saves around large components."""

from dyntri.llm import ngram_join
from dyntri.llm.components import components


def test_large_component_with_outsiders_needs_no_more_rounds(spark, monkeypatch):
    rows = 3000
    common = [f"w{i}" for i in range(19)]
    docs = [(i, " ".join([*common, f"last{i}"])) for i in range(rows)]
    outside = [(rows + i, " ".join(common[i : i + 4])) for i in range(16)]
    tail = [(rows + 100, "a b c d e"), (rows + 101, "a b c d e")]
    calls, verified = [], ngram_join.verified
    monkeypatch.setattr(ngram_join, "verified", lambda *a: calls.append(1) or verified(*a))
    found = ngram_join.join_components(spark.createDataFrame([*docs, *outside, *tail], "doc_id long, text string"), 4, 85)
    own = {r.doc_id: r.component_id for r in found.collect()}
    assert {own[i] for i, _ in docs} == {0}
    assert all(own[i] == i for i, _ in outside)
    assert own[rows + 101] == rows + 100
    assert len(calls) == 3  # two rounds of central rows (the first draws outsiders), and the product of what is left


def test_cross_product_has_each_pair_of_components_once(spark):
    comp = {1: 1, 2: 1, 3: 1, 4: 4, 5: 5, 6: 5}
    shared = spark.createDataFrame([(7, r, 20, 0, 0) for r in comp] + [(8, 1, 20, 0, 0), (8, 2, 20, 0, 0)], "h long, rep long, n long, pos int, first int")
    rows = ngram_join._open_postings(shared, spark.createDataFrame(list(comp.items()), "node long, component long"))
    got = sorted((r.a, r.b) for r in ngram_join._cross_product(rows, 85).collect())
    assert got == [(a, b) for a in comp for b in comp if a < b and comp[a] != comp[b]]


def test_components_of_chains_and_none(spark):
    links = [(i, i + 1) for i in range(10, 20)] + [(33, 31), (31, 33), (40, 40)]
    found = {r.node: r.component for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert found == {**{i: 10 for i in range(10, 21)}, 31: 31, 33: 31}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
