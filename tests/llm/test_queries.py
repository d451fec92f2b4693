"""The registered queries on whole small tables: held against their DuckDB twins, or against brute force where SQL has no form."""

import collections
import math
import zlib

import duckdb
import numpy as np
import pandas as pd
import pytest

import corpus_pipeline
from dyntri.llm import queries

from .test_operators import WORD, low

SF = "/root/testdata/sf0.001"
TABLES = ("documents", "pages", "conversations", "benchmark")


def rows_of(df):
    """Rows as sorted tuples of strings, columns by name, nulls alike."""
    cells = df[sorted(df.columns)].astype(object).itertuples(index=False)
    return sorted(tuple("null" if pd.isna(v) else str(int(v) if isinstance(v, float) else v) for v in r) for r in cells)


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_queries_equal_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want, got = con.execute(queries.oracle_sql()[name]).df(), queries.queries()[name](spark, SF).toPandas()
    assert sorted(got.columns) == sorted(want.columns) and rows_of(got) == rows_of(want)


def documents(spark):
    return [(r.doc_id, r.text or "", r.source) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "source").collect()]


def test_mixing_query(spark):
    docs, got = documents(spark), queries.op6_source_mixing(spark, SF).collect()
    size = {i: len(WORD.findall(t)) for i, t, _ in docs}
    sources = sorted({s for _, _, s in docs if s is not None}) + [None] * any(s is None for _, _, s in docs)
    whole = {s: sum(size[i] for i, _, own in docs if own == s) for s in sources}
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(sources)}
    goal, rest, left = {}, list(sources), 1.5 * sum(whole.values())
    while over := [s for s in rest if left * weight[s] / sum(weight[r] for r in rest) > 2 * whole[s]]:
        for s in over:
            goal[s] = 2.0 * whole[s]
        rest, left = [s for s in rest if s not in over], left - sum(goal[s] for s in over)
    goal |= {s: left * weight[s] / sum(weight[r] for r in rest) for s in rest}
    source, taken = {i: s for i, _, s in docs}, collections.Counter()
    assert sorted(r.doc_id for r in got) == sorted(size)
    for r in got:
        s = source[r.doc_id]
        assert (r["size"], r.source_size) == (size[r.doc_id], whole[s]) and math.isclose(r.target, goal[s], rel_tol=1e-12) and 0 <= r.taken <= 2 * r["size"]
        taken[s] += r.taken
    assert all(abs(taken[s] - goal[s]) <= 1 for s in sources)


def test_scoring_query(spark):
    docs, got = documents(spark), {r.doc_id: r for r in queries.op7_lm_scoring(spark, SF).collect()}
    held = {i: zlib.crc32(str(i).encode()) % 5 == 1 for i, _, _ in docs}
    tokens = {i: [*WORD.findall(low(t)), None] for i, t, _ in docs}
    count = collections.Counter(w for i, ws in tokens.items() if not held[i] for w in ws)
    n = sum(count.values())
    assert set(got) == set(tokens)
    for i, ws in tokens.items():
        r, base = got[i], sum(math.log10((count[w] + 0.5) / (n + 0.5 * (len(count) + 1))) for w in ws)
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[i], len(ws), sum(count[w] > 0 for w in ws), n)
        assert math.isclose(r.base_score, base, rel_tol=1e-9) and math.isfinite(r.score) and r.score < 0


def test_token_query(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    tok, start = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")), 0
    got = {r.doc_id: r for r in queries.op8_token_files(spark, SF).collect()}
    docs = sorted(documents(spark))
    assert set(got) == {i for i, _, _ in docs}
    for i, t, _ in docs:
        ids = np.array(tok.encode(t, add_special_tokens=False).ids + [2], "<u4")
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)


def test_pipeline_of_an_empty_table_and_of_nulls(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    d = docs.limit(0)
    for _, stage in corpus_pipeline.STAGES:
        d = stage(spark, d, SF)
    assert d.count() == 0
    d = spark.createDataFrame([(None,) * len(docs.columns)] * 2, docs.schema)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, d, SF).columns == docs.columns, name
