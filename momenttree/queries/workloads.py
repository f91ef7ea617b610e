"""The experiments as registered queries: what does not depend on the clock, or is far from depending on it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momenttree.operators import moments as M
from momenttree.queries import query
from momenttree.queries.shared import WORDS, vocab_sql
from momenttree.workloads import experiments as E

_ABSTRACTS = f"tok AS (SELECT doc_id, unnest(words) AS term FROM (SELECT doc_id, {WORDS} AS words FROM documents) WHERE len(words) BETWEEN 50 AND 500), cnt AS (SELECT doc_id, term, count(*) AS c FROM tok GROUP BY ALL)"
FRACTIONS = (0.25, 0.5, 1.0)
SIZES = (100, 400)
_REFUSED = int((M.BLOCK_BYTES / 8) ** 0.5)


def _rows(spark: SparkSession, rows: list[dict], ddl: str) -> DataFrame:
    names = [c.split()[0] for c in ddl.split(", ")]
    return spark.createDataFrame([tuple(r[n] for n in names) for r in rows], ddl)


@query("SELECT method, slower_than_lean FROM (VALUES ('lean', false), ('pair_network_em', true), ('recursive_lda', true), ('supertopic_gibbs', true), ('nested_partition_gibbs', true)) t(method, slower_than_lean)")
def workload_runtime(spark: SparkSession, sf: str) -> DataFrame:
    """Total time of every method, a token and at full sweeps: all are slower than the lean one."""
    corpus = E.prepare(spark, sf, "titles", top=150)
    E.methods(3, 2)["lean"](corpus)  # what is compiled once is not counted
    rows = E.total_runtime([corpus], width=3, sweeps=1)
    cost = {r["method"]: r["seconds_full_sweeps"] / r["tokens"] for r in rows}
    return spark.createDataFrame([(m, bool(c > cost["lean"])) for m, c in cost.items()], "method string, slower_than_lean boolean")


@query(f"WITH {_ABSTRACTS}, {vocab_sql(300)}, lens AS (SELECT doc_id, sum(c) AS l FROM cnt JOIN vocab USING (term) GROUP BY doc_id HAVING sum(c) >= 3) SELECT f AS fraction, count(*) AS docs, CAST(sum(l) AS DOUBLE) AS tokens, 4 AS scans FROM lens CROSS JOIN (VALUES {', '.join(f'(CAST({f} AS DOUBLE))' for f in FRACTIONS)}) t(f) WHERE (doc_id * 48271) % 1000 < 1000 * f GROUP BY f")
def workload_fraction(spark: SparkSession, sf: str) -> DataFrame:
    """More documents: the same number of scans."""
    rows = E.sweep(E.prepare(spark, sf, "abstracts", top=300, stop=False), "fraction", list(FRACTIONS), width=3)
    return _rows(spark, [r | {"fraction": float(r["value"])} for r in rows], "fraction double, docs bigint, tokens double, scans int")


@query("SELECT 'height' AS factor, h AS value, 2 * h AS scans FROM (VALUES (1), (2), (3)) t(h) UNION ALL SELECT 'width', w, 4 FROM (VALUES (2), (3), (4)) t(w)")
def workload_shape(spark: SparkSession, sf: str) -> DataFrame:
    """Two scans a level, whatever the width."""
    corpus = E.prepare(spark, sf, "abstracts", top=300)
    rows = E.sweep(corpus, "height", [1, 2, 3], width=2) + E.sweep(corpus, "width", [2, 3, 4], height=2)
    return _rows(spark, rows, "factor string, value int, scans int")


_SIZED = ", ".join(f"({n})" for n in SIZES)


@query(f"WITH {_ABSTRACTS}, w AS (SELECT least(size, (SELECT count(DISTINCT term) FROM tok)) AS words, size FROM (VALUES {_SIZED}) t(size)) SELECT size, CAST(words AS INT) AS words, variant, CASE WHEN variant = 'dense_m2' AND words > {_REFUSED} OR variant IN ('dense', 'dense_m3') AND words > {M.DENSE_THIRD_WORDS} THEN 'VocabularyTooLarge' ELSE '' END AS stopped FROM w CROSS JOIN (VALUES ('lean'), ('dense_m2'), ('dense_m3'), ('dense')) v(variant)")
def workload_vocabulary(spark: SparkSession, sf: str) -> DataFrame:
    """Larger vocabularies: the dense variants stop, the lean one goes on."""
    rows = [r | {"size": n, "stopped": r["stopped"] or ""} for n in SIZES for r in E.vocab_sweep(spark, sf, sizes=(n,), width=3, stop=False)]
    return _rows(spark, rows, "size int, words int, variant string, stopped string")


@query("SELECT factor, value, true AS settled FROM (VALUES ('starts'), ('steps')) f(factor) CROSS JOIN (VALUES (10), (20), (30)) v(value)")
def workload_iterations(spark: SparkSession, sf: str) -> DataFrame:
    """From ten starts and ten steps on, runs agree."""
    rows = E.iteration_sweep(E.prepare(spark, sf, "abstracts", top=300), values=(10, 20, 30), runs=3, width=4)
    return _rows(spark, [r | {"settled": bool(r["variance"] < 0.01)} for r in rows], "factor string, value int, settled boolean")


@query("SELECT 1000 AS docs, true AS close UNION ALL SELECT 10000, true")
def workload_recovery(spark: SparkSession, sf: str) -> DataFrame:
    """A known tree sampled at two sizes: within twice the reference errors, less with more documents."""
    bounds = {1_000: 0.2, 10_000: 0.05}
    rows = E.recovery_study(spark)
    return _rows(spark, [r | {"close": bool(r["error"] < bounds[r["docs"]])} for r in rows], "docs int, close boolean")
