"""Building an index: chunks, entities, relations, graph, vectors."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evigraph.functions.encoder import encode
from evigraph.functions.graphs import LocalGraph
from evigraph.operators import entities as ents
from evigraph.operators import kg
from evigraph.operators.measures import Stopwatch
from evigraph.operators.textprep import chunk, ngrams, term_counts
from evigraph.runtime import written
from evigraph.specs import Config

#: A graph of at most so many edges is searched by tasks that read all of it, a share of the questions each; a larger one by joins.
LOCAL_EDGES = 2_000_000


@dataclass
class Index:
    cfg: Config
    chunks: DataFrame  # chunk_key, doc_key, chunk_no, tokens, n_tok, vec
    words: DataFrame  # chunk_key, n_tok, term, cnt
    entities: DataFrame
    nodes: DataFrame
    edges: DataFrame  # with vec
    watch: Stopwatch

    @cached_property
    def n_edges(self) -> int:
        return self.edges.count()

    @cached_property
    def numbered(self) -> DataFrame:
        """no, a, b, key, text, vec: nodes (key, text; a is 1 for a passage, b null) and edges (kind, relation, vec; a and b are the numbers of their ends),
        each numbered in the order of keys. Written once, for tasks that hold the whole graph."""
        no = lambda by: (F.row_number().over(Window.orderBy(by)) - 1).alias("no")
        nodes = written(self.nodes.select(no("node_key"), (F.col("kind") == "passage").cast("int").alias("a"), F.lit(None).cast("int").alias("b"), F.col("node_key").alias("key"), "text", F.lit(None).cast("array<float>").alias("vec")), "numbered")
        end = lambda c, out: nodes.groupBy(F.col("key").alias(c)).agg(F.max("no").alias(out))
        ends = self.edges.select("edge_id", "src", "dst", no("edge_id")).join(end("src", "a"), "src", "left").join(end("dst", "b"), "dst", "left").select("edge_id", "no", "a", F.coalesce("b", F.lit(-1)).alias("b"))
        return written(nodes.unionByName(self.edges.join(ends, "edge_id").select("no", "a", "b", F.col("kind").alias("key"), F.col("relation").alias("text"), "vec")), "graph")


class Strings:
    """An Arrow column, a string at a time."""

    def __init__(self, column: pa.Array):
        self.column = column

    def __len__(self) -> int:
        return len(self.column)

    def __getitem__(self, i: int) -> str:
        return self.column[int(i)].as_py()


@dataclass
class LocalIndex:
    """The graph as arrays, in the order of keys, in a task that was dealt all its rows."""

    keys: Strings
    passage: np.ndarray
    text: Strings
    ends: np.ndarray
    kinds: pa.Array
    relations: Strings
    vecs: np.ndarray
    numbers: dict[tuple, np.ndarray] = field(default_factory=dict)

    @classmethod
    def of(cls, batches: Iterator[pa.RecordBatch], n_edges: int, dim: int) -> "LocalIndex":
        """From rows of ``Index.numbered`` in any order; vectors are put in place as they come."""
        ends, vecs = np.full((n_edges, 2), -1, np.int64), np.zeros((n_edges, dim), np.float32)
        nodes: list[pa.RecordBatch] = []
        edges: list[pa.RecordBatch] = []
        for b in batches:
            link = b.filter(pc.is_valid(b["b"]))
            at = link["no"].to_numpy()
            ends[at] = np.column_stack([pc.fill_null(link[c], -1).to_numpy() for c in ("a", "b")])
            vecs[at] = link["vec"].flatten().to_numpy().reshape(-1, dim)
            edges.append(pa.RecordBatch.from_arrays([link["no"], link["key"].dictionary_encode(), link["text"]], names=["no", "key", "text"]))
            nodes.append(b.filter(pc.is_null(b["b"])).select(["no", "a", "key", "text"]))
        if (ends < 0).any():
            raise KeyError("an edge ends at no node")

        def part(rows: list[pa.RecordBatch], *columns: str) -> list[pa.Array]:
            t = pa.Table.from_batches(rows).unify_dictionaries()
            at = pc.sort_indices(t["no"])
            return [pa.concat_arrays(t[c].chunks).take(at) for c in columns]

        kinds, relations = part(edges, "key", "text")
        passage, keys, text = part(nodes, "a", "key", "text")
        return cls(Strings(keys), passage.to_numpy() == 1, Strings(text), ends, kinds, Strings(relations), vecs)

    def edge_id(self, e: int) -> str:
        a, b = self.ends[e]
        return f"{self.keys[a]}|{self.relations[e]}|{self.keys[b]}"

    def of_kinds(self, *kinds: str) -> np.ndarray:
        """Numbers of the edges of some kinds."""
        if kinds not in self.numbers:
            self.numbers[kinds] = np.flatnonzero(np.isin(self.kinds.indices.to_numpy(), [i for i, k in enumerate(self.kinds.dictionary.to_pylist()) if k in kinds]))
        return self.numbers[kinds]

    @cached_property
    def held(self) -> tuple[np.ndarray, np.ndarray]:
        """Passages and, beside each, the other nodes that it is tied to, one by one."""
        a, b = self.ends.T
        one, two = self.passage[b] & ~self.passage[a], self.passage[a] & ~self.passage[b]
        return np.concatenate([b[one], a[two]]), np.concatenate([a[one], b[two]])

    @cached_property
    def graph(self) -> LocalGraph:
        return LocalGraph(len(self.keys), self.ends)

    @cached_property
    def linked(self) -> LocalGraph:
        """With the pseudo node, which every passage is tied to; its edges come last."""
        p = np.flatnonzero(self.passage)
        return LocalGraph(len(self.keys) + 1, np.vstack([self.ends, np.column_stack([np.full(len(p), len(self.keys)), p])]))


def build(corpus: DataFrame, cfg: Config = Config(), extract_entities=None, extractor=None, synonyms: bool = True) -> Index:
    """All stages of data preparation, each written once; ``corpus``: doc_key, text."""
    watch = Stopwatch()
    with watch.stage("chunk and encode"):
        cut = chunk(corpus, cfg.chunk)
        chunks = written(encode(cut.withColumn("_x", F.array_join("tokens", " ")), "_x", cfg.dim).drop("_x"), "chunks")
    with watch.stage("entities"):
        grams = ngrams(chunks, 1)
        words = written(term_counts(grams).select("chunk_key", "n_tok", "term", "cnt"), "words")
        if extract_entities is not None:
            chosen = extract_entities(chunks)
        else:
            chosen = ents.select_entities(ents.score_chunks(chunks, cfg.entity), cfg.entity)
        chosen = written(chosen, "entities")
    with watch.stage("relations and graph"):
        relations = kg.extract_relations(chunks, chosen, extractor)
        syn = None
        if synonyms:
            from evigraph.operators.synonyms import edges_lsh

            named = encode(chosen.select("term").distinct(), "term", cfg.dim).select(kg.entity_key().alias("node_key"), "vec")
            syn = written(edges_lsh(written(named, "named"), cfg.phi), "synonyms")
        nodes, edges = kg.assemble(chunks, chosen, relations, syn, cfg.head_words)
        nodes = written(nodes, "nodes")
        edges = written(encode(edges, "fact_text", cfg.dim), "edges")
    return Index(cfg, chunks, words, chosen, nodes, edges, watch)
