"""The experiments, re-expressed on the given tables.  Each returns rows that say what was varied and what was measured.

All methods see the same bags; Gibbs chains run SWEEPS sweeps instead of 1000 unless told otherwise, and report both the
time taken and the time scaled to 1000 sweeps, named as such.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from momenttree.baselines import gibbs, network
from momenttree.evaluation import intrusion, measures
from momenttree.evaluation.cost import Ledger
from momenttree.functions import text as T
from momenttree.operators import corpus as C
from momenttree.operators import moments as M
from momenttree.operators import phrases as P
from momenttree.operators.tree import TopicTree, collapse
from momenttree.plans import build as B
from momenttree.runtime import spread, stored
from momenttree.sources import tables

SWEEPS = 5
FULL_SWEEPS = 1_000


def titles(spark: SparkSession, sf: str) -> DataFrame:
    return tables.titles(spark, sf)


def abstracts(spark: SparkSession, sf: str) -> DataFrame:
    """Documents of 50 to 500 words."""
    n = F.size(T.words(F.col("text")))
    return tables.read_table(spark, sf, "documents").where((n >= 50) & (n <= 500)).select("doc_id", "text")


def articles(spark: SparkSession, sf: str) -> DataFrame:
    return tables.pages_text(spark, sf).select("doc_id", "text")


def everything(spark: SparkSession, sf: str) -> DataFrame:
    """All documents and conversations; stemmed by `prepare`."""
    talks = tables.conversation_docs(spark, sf).select((-1 - F.col("doc_id")).alias("doc_id"), "text")
    return tables.read_table(spark, sf, "documents").select("doc_id", "text").union(talks)


CORPORA: dict[str, Callable[[SparkSession, str], DataFrame]] = {"titles": titles, "abstracts": abstracts, "articles": articles, "everything": everything}


@dataclass
class Corpus:
    name: str
    vocab: DataFrame
    bags: DataFrame
    v: int
    n_docs: int
    n_tokens: float


def prepare(spark: SparkSession, sf: str, name: str, *, top: int = 1_000, stop: bool = True) -> Corpus:
    """Stop words out, documents under three tokens out; the largest corpus is stemmed."""
    docs = CORPORA[name](spark, sf)
    tok = stored(C.tokens(spread(docs), stop=T.stop_list() if stop else None, stems=name == "everything"), name)
    vocab = stored(C.vocabulary(tok, top=top), "vocab")
    v = vocab.count()
    bags = stored(C.bags(tok, vocab, size=v), "bags")
    totals = bags.agg(F.count("*"), F.sum("len")).first()
    return Corpus(name, vocab, bags, v, totals[0], float(totals[1] or 0))


def edges_of(corpus: Corpus) -> DataFrame:
    """The co-occurrence network, weighed as counts."""
    scale = corpus.n_tokens
    return stored(M.second_moment(corpus.bags, corpus.v).select("x1", "x2", (F.col("v") * scale).alias("w")).where("w > 0"), "edges")


#: Methods whose time grows with sweeps.
SAMPLERS = ("recursive_lda", "supertopic_gibbs", "nested_partition_gibbs")
ALL_METHODS = ("lean", "pair_network_em", *SAMPLERS)
#: The four of the sweeps and studies; the nested sampler is too slow for them.
STUDIED = ALL_METHODS[:4]
#: Documents that the sequential sampler gets in the study of total time.
NESTED_DOCS = 500


def sampled(bags: DataFrame, n: int) -> DataFrame:
    """n documents of the smallest hashes: a sample that does not depend on partitions."""
    return stored(bags.orderBy(F.xxhash64("doc_id"), "doc_id").limit(n), "sampled_bags")


def methods(width: int, height: int, seed: int = 0, sweeps: int = SWEEPS) -> dict[str, Callable[[Corpus], TopicTree]]:
    """Name -> builder of a tree."""
    widths = (width,) * height

    def supertopic(c: Corpus) -> TopicTree:
        model = gibbs.supertopic_gibbs(c.bags, c.v, n_super=width, n_sub=width ** max(height, 2), iters=sweeps, seed=seed)
        tree = gibbs.strongest_subtopics(model, width)
        return tree if height > 1 else collapse(tree, tree.level(1))

    return {
        "lean": lambda c: B.build_tree(c.bags, c.v, width=width, height=height, seed=seed),
        "pair_network_em": lambda c: network.pair_network_em(edges_of(c), c.v, widths=widths, iters=20, seed=seed),
        "recursive_lda": lambda c: gibbs.recursive_lda(c.bags, c.v, widths=widths, iters=sweeps, seed=seed),
        "supertopic_gibbs": supertopic,
        "nested_partition_gibbs": lambda c: gibbs.nested_partition_gibbs(sampled(c.bags, NESTED_DOCS), c.v, height=height, iters=sweeps, seed=seed)[0],
    }


def timed(run: Callable[[], object]) -> tuple[object, float]:
    began = time.perf_counter()
    return run(), time.perf_counter() - began


def total_runtime(corpora: list[Corpus], *, width: int = 5, height: int = 2, names: tuple[str, ...] = ALL_METHODS, sweeps: int = SWEEPS) -> list[dict]:
    """Seconds and tokens a second of full constructions; Gibbs seconds also scaled to FULL_SWEEPS sweeps.

    The nested sampler sees NESTED_DOCS documents; its seconds a token compare it with the others.
    """
    rows = []
    for c in corpora:
        for name in names:
            tree, s = timed(lambda c=c, name=name: methods(width, height, sweeps=sweeps)[name](c))
            tokens = float(sampled(c.bags, NESTED_DOCS).agg(F.sum("len")).first()[0] or 0) if name == "nested_partition_gibbs" else c.n_tokens
            scaled = s * FULL_SWEEPS / sweeps if name in SAMPLERS else s
            rows.append({"corpus": c.name, "method": name, "docs": c.n_docs, "tokens": tokens, "words": c.v, "nodes": len(tree.nodes), "seconds": s, "seconds_full_sweeps": scaled, "tokens_per_second": tokens / s})
    return rows


def fraction_of(bags: DataFrame, share: float) -> DataFrame:
    """A share of the documents, by a multiplicative hash of their ids."""
    return bags.where(F.pmod(F.col("doc_id") * 48_271, F.lit(1000)) < int(1000 * share))


def sweep(corpus: Corpus, factor: str, values: list, *, names: tuple[str, ...] = ("lean",), sweeps: int = SWEEPS, **fixed) -> list[dict]:
    """Seconds of constructions with one of: fraction (of documents), height, width, and for the lean method starts, steps, alpha0."""
    rows = []
    for value in values:
        settings = {"width": 5, "height": 2} | fixed
        c = corpus
        if factor == "fraction":
            bags = stored(fraction_of(corpus.bags, value), "fraction")
            totals = bags.agg(F.count("*"), F.sum("len")).first()
            c = replace(corpus, bags=bags, n_docs=totals[0], n_tokens=float(totals[1] or 0))
        else:
            settings[factor] = value
        for name in names:
            ledger = Ledger()
            if name == "lean":
                run = lambda c=c, settings=settings, ledger=ledger: B.build_tree(c.bags, c.v, ledger, **settings)
            else:
                run = lambda c=c, settings=settings, name=name: methods(settings["width"], settings["height"], sweeps=sweeps)[name](c)
            tree, s = timed(run)
            scaled = s * FULL_SWEEPS / sweeps if name in SAMPLERS else s
            rows.append({"factor": factor, "value": value, "method": name, "docs": c.n_docs, "tokens": c.n_tokens, "seconds": s, "seconds_full_sweeps": scaled, "scans": ledger.scans if name == "lean" else None, "nodes": len(tree.nodes)})
    return rows


def vocab_sweep(spark: SparkSession, sf: str, name: str = "abstracts", sizes: tuple[int, ...] = (50, 100, 200, 400, 1_000, 5_000, 20_000, 50_000), variants: tuple[str, ...] = ("lean", "dense_m2", "dense_m3", "dense"), width: int = 5, stop: bool = True) -> list[dict]:
    """Seconds of each variant by vocabulary size, or what stops it."""
    rows = []
    for size in sizes:
        c = prepare(spark, sf, name, top=size, stop=stop)
        for variant in variants:
            try:
                _, s = timed(lambda c=c, variant=variant: B.decompose(c.bags, c.v, width, variant=variant))
                rows.append({"words": c.v, "variant": variant, "seconds": s, "stopped": None})
            except MemoryError as why:
                rows.append({"words": c.v, "variant": variant, "seconds": None, "stopped": type(why).__name__})
    return rows


def variance_study(corpora: list[Corpus], *, runs: int = 10, width: int = 5, height: int = 1, names: tuple[str, ...] = STUDIED, docs: int = 10_000, sweeps: int = SWEEPS) -> list[dict]:
    """Mean divergence of matched topics over all ordered pairs of runs that differ in their seed, on a sample of documents."""
    rows = []
    for c in corpora:
        c = replace(c, bags=sampled(c.bags, docs)) if c.n_docs > docs else c
        for m in names:
            rows.append({"corpus": c.name, "method": m, "runs": runs, "pairs": runs * (runs - 1), "variance": measures.variance([methods(width, height, seed=s, sweeps=sweeps)[m](c) for s in range(runs)])})
    return rows


def iteration_sweep(corpus: Corpus, *, values: tuple[int, ...] = (1, 2, 5, 10, 20, 30), runs: int = 4, width: int = 5) -> list[dict]:
    """Variance and seconds of the lean method by starts (30 steps) and by steps (30 starts)."""
    rows = []
    for factor, other in (("starts", "steps"), ("steps", "starts")):
        for value in values:
            trees, s = timed(lambda factor=factor, other=other, value=value: [B.build_tree(corpus.bags, corpus.v, width=width, height=1, seed=r, **{factor: value, other: 30}) for r in range(runs)])
            rows.append({"factor": factor, "value": value, "variance": measures.variance(trees), "seconds": s / runs})
    return rows


def ranked_phrases(spark: SparkSession, sf: str, corpus: Corpus, tree: TopicTree, *, min_support: int = 20, max_len: int | None = None, top: int = 10) -> dict[str, list[str]]:
    """The best phrases of every node under its parent: top for each node, on the driver."""
    sentences = stored(C.sentence_rows(spread(CORPORA[corpus.name](spark, sf))), "sentences")
    words = tree.words_df(spark, 1e-12).join(F.broadcast(corpus.vocab.select("term_id", "term")), "term_id").select("path", "term", "phi")
    ranked = P.rank_tree(sentences, tree.nodes_df(spark), words, corpus.n_docs, min_support=min_support, max_len=max_len, top=top)
    return {path: own["phrase"].tolist() for path, own in ranked.toPandas().sort_values("rank").groupby("path")}


def intrusion_study(spark: SparkSession, sf: str, corpora: list[Corpus], *, names: tuple[str, ...] = STUDIED, width: int = 5, height: int = 2, phrase_questions: int = 200, topic_questions: int = 160, sweeps: int = SWEEPS, min_support: int = 20) -> list[dict]:
    """F1 of both intrusion tasks with three npmi judges that differ in how easily they hesitate (they replace people)."""
    rows = []
    for corpus in corpora:
        tok = C.tokens(CORPORA[corpus.name](spark, sf))
        named = corpus.vocab.select("term_id", "term")
        pairs = measures.npmi_pairs(C.long_bags(tok, corpus.vocab, corpus.v), corpus.n_docs).join(named.toDF("x1", "a"), "x1").join(named.toDF("x2", "b"), "x2")
        npmi = {(min(r.a, r.b), max(r.a, r.b)): r.npmi for r in pairs.select("a", "b", "npmi").collect()}  # of a vocabulary of hundreds
        for name in names:
            ranked = ranked_phrases(spark, sf, corpus, methods(width, height, sweeps=sweeps)[name](corpus), min_support=min_support)
            for task, questions in (("phrase", intrusion.phrase_intrusion(ranked, phrase_questions)), ("topic", intrusion.topic_intrusion(ranked, topic_questions))):
                answers = [[intrusion.npmi_judge(q, npmi, h) for q in questions] for h in (0.0, 0.01, 0.02)]
                rows.append({"corpus": corpus.name, "method": name, "task": task, "questions": len(questions)} | intrusion.score_intrusion(questions, answers))
    return rows


def recovery_study(spark: SparkSession, *, sizes: tuple[int, ...] = (1_000, 10_000), v: int = 30, k: int = 3, length: int = 40) -> list[dict]:
    """Largest L1 error of a topic's words by corpus size, on a known tree."""
    from momenttree.operators import sampler

    truth = sampler.sample_tree((k,), v, seed=5)
    rows = []
    for n in sizes:
        bags = stored(sampler.as_bags(sampler.sample_corpus(spark, truth, n, length, seed=5)), "sampled")
        tree = B.build_tree(bags, v, width=k, height=1, alpha0=float(k))
        errors = measures.recovery_error(tree, truth)
        rows.append({"docs": n, "error": float(max(e for e, _ in errors.values())), "share_error": float(np.mean([a for _, a in errors.values()]))})
    return rows


def as_table(spark: SparkSession, rows: list[dict]) -> DataFrame:
    return spark.createDataFrame([{k: float(x) if isinstance(x, (float, np.floating)) else x for k, x in r.items()} for r in rows])
