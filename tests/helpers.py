"""A graph by hand and a comparison with DuckDB."""

import os

import duckdb

from kgreason.functions.vectors import Numeric
from kgreason.operators.graph import KnowledgeGraph


def hand_graph(spark, edges, vectors, relations, dim):
    """edges (r, h, t), vectors {id: [..]}, relations {r: [..]} in doubles."""
    triples = spark.createDataFrame([(r, "x", h, "x", t) for r, h, t in edges], "r string, h_type string, h bigint, t_type string, t bigint")
    vecs = spark.createDataFrame([(k, [float(x) for x in v]) for k, v in vectors.items()], "eid bigint, vec array<double>")
    rels = spark.createDataFrame([(k, [float(x) for x in v]) for k, v in relations.items()], "r string, vec array<double>")
    return KnowledgeGraph(triples, vecs, rels, dim, Numeric("double"))


def duck(sf):
    con = duckdb.connect()
    for name in os.listdir(sf):
        con.sql(f"create view {name.split('.')[0]} as select * from read_parquet('{sf}/{name}')")
    return con


def plain(v):
    return v.item() if hasattr(v, "item") else v


def rows_of(df):
    columns = sorted(df.columns)
    return sorted((tuple(plain(r[c]) for c in columns) for r in df.collect()), key=repr)


def duck_rows(con, sql):
    got = con.sql(sql)
    order = sorted(range(len(got.columns)), key=lambda i: got.columns[i])
    return sorted((tuple(r[i] for i in order) for r in got.fetchall()), key=repr)
