"""From a corpus to windows: segments, vectors, clusters, packing; and the two baselines over the same segments."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowforge.config import Config
from windowforge.functions.tokens import segment
from windowforge.operators import assign, baselines, isodata, objective, stats
from windowforge.operators.embed import hash_embed
from windowforge.operators.pack import pack
from windowforge.session import settled


@dataclass
class Prepared:
    segments: DataFrame  # seg_id, doc_id, seg_no, n_tokens, tokens
    vectors: DataFrame  # seg_id, vec


@dataclass
class Organized:
    prepared: Prepared
    clustering: isodata.Clustering
    manifest: DataFrame


def prepare(docs: DataFrame, config: Config = Config()) -> Prepared:
    """Text and vectors in separate tables, so that clustering and packing read no text."""
    segments = settled(segment(docs.select("doc_id", "text"), config.window, config.overlong, config.tokens).select("seg_id", "doc_id", "seg_no", "n_tokens", "tokens"), "segments")
    return Prepared(segments, settled(hash_embed(segments, config.dim, config.idf, config.signed), "vectors"))


def members_of(prepared: Prepared, membership: DataFrame) -> DataFrame:
    lengths = prepared.segments.select("seg_id", "doc_id", "seg_no", "n_tokens")
    return membership.select("seg_id", "cluster_id").join(lengths, "seg_id").join(prepared.vectors, "seg_id")


def organize(docs: DataFrame, config: Config = Config(), prepared: Prepared | None = None) -> Organized:
    kept, prepared = prepared is None, prepared or prepare(docs, config)
    clustering = isodata.fit(prepared.vectors, config, kept=kept)
    return Organized(prepared, clustering, settled(pack(members_of(prepared, clustering.membership), config), "manifest"))


def graph_paths(prepared: Prepared, k: int = 20, how: str = "auto") -> DataFrame:
    """Paths through the graph of neighbours: one walk over an exact graph, or, with more segments than one walk may hold, a walk for each
    coarse cell over a graph sought by cells; the column exact says which."""
    n = prepared.segments.count()
    whole = n <= baselines.TRAVERSE_NODES
    edges = settled(baselines.knn_graph(prepared.vectors, k, how if how != "auto" else "exact" if whole else "cells"), "edges")
    if whole:
        return settled(baselines.traverse(edges, prepared.segments.select("seg_id")), "paths")
    coarse = assign.coarse_centres(prepared.vectors.select(F.col("seg_id").alias("cluster_id"), "vec"), max(2, 4 * n // baselines.TRAVERSE_NODES))
    return settled(baselines.traverse(edges, assign.with_cells(prepared.vectors, "seg_id", coarse, 1).select("seg_id", "cell"), "cell"), "paths")


def compared(docs: DataFrame, config: Config = Config()) -> DataFrame:
    """One row of measures for each of the framework, random order and graph traversal, with the table of clusters or paths."""
    done = organize(docs, config)
    p = done.prepared
    ways = {
        "framework": done.manifest,
        "random": settled(baselines.random_windows(p.segments, config.window, config.seed), "random"),
        "graph": settled(baselines.graph_windows(p.segments, paths := graph_paths(p), config.window), "graph"),
    }
    sizes = {"framework": stats.cluster_sizes(done.clustering.membership), "graph": stats.cluster_sizes(paths, "path_id")}
    out = None
    for name, manifest in ways.items():
        row = objective.report(manifest, p.segments, p.vectors, config.window, name)
        table = stats.cluster_table(sizes.get(name, stats.cluster_sizes(paths.filter(F.lit(False)), "path_id"))).select("clusters", "largest", "median", F.col("single").alias("single_clusters"))
        row = row.crossJoin(table)
        out = row if out is None else out.unionByName(row)
    return out


def organize_domain(docs: DataFrame, domain: str, value: str, config: Config = Config()) -> DataFrame:
    """Manifest with a column of methods: one domain organised, all others, the unnamed (null) one too, in random order."""
    chosen = organize(docs.filter(F.col(domain).eqNullSafe(value)), config).manifest.select("window_id", "pos", "seg_id", "start", "offset", "n_tokens", "used", "cut").withColumn("method", F.lit("framework"))
    rest = prepare_random(docs.filter(~F.col(domain).eqNullSafe(value)), domain, config)
    return chosen.unionByName(rest.withColumn("method", F.lit("random")))


def prepare_random(docs: DataFrame, domain: str, config: Config) -> DataFrame:
    segments = segment(docs.select("doc_id", "text", domain), config.window, config.overlong, config.tokens)
    return baselines.random_windows(segments.select("seg_id", "n_tokens", domain), config.window, config.seed, within=domain)
