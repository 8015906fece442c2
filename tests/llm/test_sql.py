"""Operators against SQL on the given tables."""

import glob
import os

import duckdb
import pytest

from hyperembed.llm import quality
from hyperembed.llm.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"

#: Counts and the base rule of the quality operator; its verdict has no SQL form.
BASE = r"""
    WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
    w AS (SELECT doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w FROM d),
    lines AS (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM d),
    lines_again AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n FROM lines WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY doc_id),
    windows AS (SELECT doc_id, unnest(range(1, len(w) - 1)) AS i, w FROM w WHERE len(w) >= 3),
    counted AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, w[i:i+2]) AS n FROM windows),
    words_again AS (SELECT doc_id, count(DISTINCT k) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS k FROM counted WHERE n >= 2) GROUP BY doc_id),
    counts AS (SELECT w.doc_id, len(w.w)::BIGINT AS n_words, coalesce(list_sum([length(x) FOR x IN w.w]), 0)::BIGINT AS word_chars,
                      len(regexp_extract_all(t, '[#*$%&|<>]'))::BIGINT AS n_symbols, coalesce(l.n, 0) AS n_dup_lines, coalesce(r.n, 0) AS n_repeat_words
               FROM w LEFT JOIN lines_again l USING (doc_id) LEFT JOIN words_again r USING (doc_id))
    SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM counts"""


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        c.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM read_parquet('{p}')")
    return c


def rows(columns, records):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(repr(tuple(r[i] for i in order)) for r in records)


def same(df, duck, sql):
    result = duck.execute(sql)
    columns = [d[0] for d in result.description]
    assert sorted(df.columns) == sorted(columns)
    assert rows(df.columns, df.collect()) == rows(columns, result.fetchall())


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_against_sql(spark, duck, name):
    same(QUERIES[name](spark, SF), duck, ORACLES[name])


def test_quality_counts_against_sql(spark, duck):
    same(quality.judge(spark.read.parquet(f"{SF}/documents.parquet")).drop("quality", "kept"), duck, BASE)
