"""Codecs and searches for SQL users: register(spark) names them in a session.

wah_words(slots, n_bits) and wah_positions(payload, n_bits), deflate and inflate, the grouped wah_build(slot, n_bits), and the table functions
wah_members(payload, n_bits) and kronecker(scale, edge_factor, seed). The set lane in `sizes` needs none of them. bfs_sql makes a search's
tree a view.
"""

from __future__ import annotations

import zlib

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..operators.layout import build
from ..operators.traverse import bfs
from ..sources.graphs import Tuples
from ..sources.kronecker import edge_of
from .codecs import Wah


def register(spark: SparkSession, width: int = 32) -> None:
    wah = Wah(width)

    @F.pandas_udf("array<long>")
    def wah_words(slots: pd.Series, n_bits: pd.Series) -> pd.Series:
        return pd.Series([wah.words(np.asarray(s, dtype=np.int64), int(n)) for s, n in zip(slots, n_bits, strict=True)])

    @F.pandas_udf("array<long>")
    def wah_positions(payload: pd.Series, n_bits: pd.Series) -> pd.Series:
        return pd.Series([wah.decode(p, int(n)) for p, n in zip(payload, n_bits, strict=True)])

    @F.pandas_udf("binary")
    def deflate(data: pd.Series, level: pd.Series) -> pd.Series:
        return pd.Series([None if d is None else zlib.compress(d, int(k)) for d, k in zip(data, level, strict=True)])

    @F.pandas_udf("binary")
    def inflate(data: pd.Series) -> pd.Series:
        return pd.Series([None if d is None else zlib.decompress(d) for d in data])

    @F.pandas_udf("binary")
    def wah_build(slot: pd.Series, n_bits: pd.Series) -> bytes:
        return wah.encode(np.sort(slot.to_numpy(dtype=np.int64)), int(n_bits.iloc[0]))

    class Kronecker:
        def eval(self, scale: int, edge_factor: int, seed: int):
            for i in range(edge_factor << scale):
                yield edge_of(i, scale, seed)

    class Members:
        def eval(self, payload: bytes, n_bits: int):
            for slot in wah.decode(payload, n_bits).tolist():
                yield (slot,)

    for name, fn in (("wah_words", wah_words), ("wah_positions", wah_positions), ("deflate", deflate), ("inflate", inflate), ("wah_build", wah_build)):
        spark.udf.register(name, fn)
    spark.udtf.register("kronecker", F.udtf(Kronecker, returnType="u: long, v: long"))
    spark.udtf.register("wah_members", F.udtf(Members, returnType="slot: long"))


def bfs_sql(spark: SparkSession, table: str, source: int, view: str = "tree", p: int = 8, method: str = "relational") -> None:
    """Searches the undirected graph whose edges (u, v) a table or view holds, with ids from 0 on, and names the tree (vid, level, parent)."""
    edges = spark.table(table).select("u", "v")
    n = edges.agg(F.max(F.greatest("u", "v"))).first()[0]
    n = max(source, -1 if n is None else n) + 1
    bfs(build(Tuples(edges, n, source), p), method=method).tree.createOrReplaceTempView(view)
