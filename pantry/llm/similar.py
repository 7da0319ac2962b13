"""Groups of near-duplicates by the exact Jaccard similarity of word-shingle sets.

Two sets that reach the similarity share a shingle among the first few of both (all sets in one order,
frequent shingles last), so documents meet in the cells of their prefix shingles. A pair is dropped only
by a bound that no pair over the similarity exceeds: the sizes, and sketches of one parity bit a place.
What is left is verified on whole texts.

Dense groups never list their pairs. First each cell names one link a document at most, to the first
near it; the components of these unverified links, and of those that a caller brings, are families, whose texts meet once (in blocks, each with the
family's first document) and are verified until each block's groups are known. Then every pair of a
cell whose documents are still apart, and have not met in a block, is verified: so no pair is missed.

Defined results: equal texts are one document from the start; null and empty texts are equal to each other
and to nothing else; rows without an id are in no group; rows that repeat an id with different texts are
a document for each text; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pantry.llm import text as tx
from pantry.llm.components import components
from pantry.llm.ranks import meet
from pantry.session import discard, materialize, release

#: Documents whose shingles are counted for the order, and frequent shingles that every task knows.
SAMPLE = 4000
FREQUENT = 50_000
#: Documents and shingles of a block of a family; comparisons held in memory at once.
FAMILY = 512
FAMILY_SHINGLES = 4_000_000
AT_ONCE = 1 << 20
LEAST_BITS, MOST_BITS = 64, 8192


def shingle_sets(texts: pa.Array, words: int) -> list[np.ndarray]:
    """The sorted different 64-bit hashes of each text's word shingles; a shorter text is one shingle, an empty one none.

    Different words of the batch are hashed once; a shingle mixes the hashes of its words by their places.
    """
    codes, counts, distinct = tx.batch_words(texts)
    w = tx.word_hashes(distinct, 11)[codes] if len(codes) else np.zeros(0, np.uint64)
    place = _mixed(np.arange(1, words + 1)) | np.uint64(1)
    windows = max(0, len(w) - words + 1)
    mixed = np.zeros(windows, np.uint64)
    for j in range(words):
        mixed += w[j : windows + j] * place[j]
    mixed = _mixed(mixed.view(np.int64))
    out = []
    for e, n in zip(np.cumsum(counts).tolist(), counts.tolist()):
        if n >= words:
            out.append(np.unique(mixed[e - n : e - words + 1]))
        else:
            short = (w[e - n : e] * place[:n]).sum(dtype=np.uint64, keepdims=True) + np.uint64(n)
            out.append(_mixed(short.view(np.int64)) if n else short[:0])
    return out


def _sets(column: pa.Array, words: int) -> list[np.ndarray]:
    """The sets of a column, some megabytes of text at a time."""
    texts = tx.large(column)
    return [u for a, b in tx.pieces(texts) for u in shingle_sets(texts.slice(a, b - a), words)]


def sketch(u: np.ndarray) -> bytes:
    """At each bit the parity of the number of the set's hashes there; more bits for larger sets.

    Two sketches differ in no more bits than the sets in hashes, also after one is folded to the width
    of the other.
    """
    bits = LEAST_BITS
    while bits < 3 * len(u) and bits < MOST_BITS:
        bits *= 2
    return np.packbits((np.bincount((u % np.uint64(bits)).astype(np.int64), minlength=bits) & 1).astype(np.uint8), bitorder="little").tobytes()


class Sketches:
    """Sketches of many sets, zero-filled to one width."""

    def __init__(self, sketches: list[bytes], sizes: np.ndarray, similarity: float):
        self.words = np.array([len(s) // 8 for s in sketches], np.int64)
        wide = int(self.words.max(initial=1)) * 8
        self.rows = np.frombuffer(b"".join(s.ljust(wide, b"\0") for s in sketches), np.uint64).reshape(len(sketches), -1)
        self.sizes, self.share = sizes.astype(np.int64), (1 - similarity) / (1 + similarity)

    def near(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Which pairs a[i], b[i] can reach the similarity: none that does is left out.

        |x - y| + |y - x| = |x| + |y| - 2 common, and common >= similarity / (1 + similarity) * (|x| + |y|).
        """
        most = (self.sizes[a] + self.sizes[b]) * self.share + 1e-6
        out = np.abs(self.sizes[a] - self.sizes[b]) <= most
        low = np.minimum(self.words[a], self.words[b])
        for w in np.unique(low[out]):
            at = np.flatnonzero(out & (low == w))
            for k in range(0, len(at), AT_ONCE // 8):
                some = at[k : k + AT_ONCE // 8]
                x, y = (np.bitwise_xor.reduce(self.rows[i[some]].reshape(len(some), -1, w), axis=1) for i in (a, b))
                out[some] = np.bitwise_count(x ^ y).sum(1) <= most[some]
        return out


def whole_cells(batches, names: tuple[str, ...]):
    """Tables of whole cells of a sorted stream: the last cell of a batch may go on in the next."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        held.append(b)
        t = pa.Table.from_batches(held)
        open_ = np.logical_and.reduce([k == k[-1] for k in (t.column(c).to_numpy() for c in names)])
        at = int(np.flatnonzero(open_)[0])
        if at:
            yield t.slice(0, at)
        held = t.slice(at).combine_chunks().to_batches()
    if held:
        yield pa.Table.from_batches(held)


def starts(t: pa.Table, names: tuple[str, ...]) -> np.ndarray:
    """Where the cells of a sorted table begin."""
    keys = [t.column(c).to_numpy() for c in names]
    return np.concatenate([[0], np.flatnonzero(np.logical_or.reduce([k[1:] != k[:-1] for k in keys])) + 1])


def _mixed(v: np.ndarray) -> np.ndarray:
    """Ids spread over 64 bits."""
    v = v.astype(np.int64).view(np.uint64) + np.uint64(0x9E3779B97F4A7C15)
    v = (v ^ (v >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    v = (v ^ (v >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return v ^ (v >> np.uint64(31))


def _frequent(one: DataFrame, words: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that come often in a bounded sample, in order, and how often; the order of prefixes, not their use, depends on it."""
    share = max(1, n // SAMPLE)

    def run(batches):
        for b in batches:
            sets = _sets(b.column(1), words)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([*sets, np.zeros(0, np.uint64)]).view(np.int64))], ["h"])

    some = one.where(F.pmod(F.xxhash64("node"), F.lit(share)) == 0).mapInArrow(run, "h long")
    often = some.groupBy("h").agg(F.count("*").alias("n")).where("n > 2").orderBy(F.col("n").desc(), "h").limit(FREQUENT).collect()  # at most FREQUENT rows
    h = np.array([r["h"] for r in often], np.int64).view(np.uint64)
    order = np.argsort(h)
    return h[order], np.array([r["n"] for r in often], np.int64)[order]


def _prefixes(one: DataFrame, words: int, similarity: float, n: int) -> DataFrame:
    """(node, size, sketch, prefix): of two sets that reach the similarity the prefixes share a shingle."""
    often, count = _frequent(one, words, n)
    often, count = np.append(often, np.uint64(2**64 - 1)), np.append(count, 0)

    def run(batches):
        for b in batches:
            sizes, sketches, first = [], [], []
            for u in _sets(b.column(1), words):
                at = np.minimum(np.searchsorted(often, u), len(often) - 1)
                weight = np.where(often[at] == u, count[at], 0)
                most = len(u) - int(np.ceil(similarity * len(u) - 1e-9)) + 1
                sizes.append(len(u))
                sketches.append(sketch(u))
                first.append((u[np.lexsort((u, weight))[:most]] if len(u) else np.zeros(1, np.uint64)).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sizes, pa.int64()), pa.array(sketches, pa.binary()), pa.array(first, pa.binary())], ["node", "size", "sketch", "prefix"])

    return one.mapInArrow(run, "node long, size long, sketch binary, prefix binary")


def _cells(prefixes: DataFrame) -> DataFrame:
    """(h, node, n): the nodes that share a prefix shingle, cells of the same nodes once."""

    def spread(batches):
        for b in batches:
            sets = [np.frombuffer(x, np.int64) for x in b.column(1).to_pylist()]
            node = np.repeat(b.column(0).to_numpy(), [len(s) for s in sets])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([*sets, np.zeros(0, np.int64)])), pa.array(node)], ["h", "node"])

    def shared(batches):
        for t in whole_cells(batches, ("h",)):
            t = t.take(pa.array(starts(t, ("h", "node"))))  # a node once
            start = starts(t, ("h",))
            h, node = t.column("h").to_numpy(), t.column("node").to_numpy()
            n = np.diff([*start, len(h)])
            of = np.repeat(np.arange(len(n)), n)
            head = np.zeros(len(h), bool)
            head[start] = True
            same = np.add.reduceat(_mixed(node), start).view(np.int64)
            keep = n[of] > 1
            yield pa.RecordBatch.from_arrays([pa.array(c[keep]) for c in (h, node, n[of], same[of], head)], ["h", "node", "n", "same", "head"])

    sent = prefixes.select("node", "prefix").mapInArrow(spread, "h long, node long")
    met = sent.repartition("h").sortWithinPartitions("h", "node").mapInArrow(shared, "h long, node long, n long, same long, head boolean")
    met = materialize(met, "met")
    # the head of a cell is its least node
    once = met.where("head").groupBy("same", "n", "node").agg(F.min("h").alias("h")).select("h")
    out = materialize(met.join(once, "h", "left_semi").select("h", "node", "n"), "cells")
    discard(met)
    return out


def _links_of_cells(cells: DataFrame, prefixes: DataFrame, similarity: float, block: int = 2048) -> DataFrame:
    """(a, b): in each cell a link a node at most, to the first node near it, in order. Cells over ``block`` nodes are cut."""
    key = ("h", "i")
    rows = cells.withColumn("i", F.pmod(F.xxhash64("node"), F.ceil(F.col("n") / block)).cast("int"))
    dealt = rows.join(prefixes.select("node", "size", "sketch"), "node").select(*key, "node", "size", "sketch").repartition(*key).sortWithinPartitions(*key, "node")

    def compare(batches):
        for t in whole_cells(batches, key):
            node = t.column("node").to_numpy()
            have = Sketches(t.column("sketch").to_pylist(), t.column("size").to_numpy(), similarity)
            start = starts(t, key)
            cell = np.repeat(np.arange(len(start)), np.diff([*start, len(node)]))
            rest, out = np.arange(len(node)), [np.zeros((0, 2), np.int64)]
            while len(rest):  # the first of every cell against the others of the cell
                lead = np.concatenate([[True], cell[rest][1:] != cell[rest][:-1]])
                first = rest[lead][np.cumsum(lead) - 1]
                a, b = first[~lead], rest[~lead]
                hit = have.near(a, b)
                out.append(np.stack([node[a[hit]], node[b[hit]]], 1))
                rest = b[~hit]
            found = np.unique(np.concatenate(out), axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(found[:, 0]), pa.array(found[:, 1])], ["a", "b"])

    return dealt.mapInArrow(compare, "a long, b long").distinct()


def _jaccard_reaches(u: np.ndarray, v: np.ndarray, similarity: float) -> bool:
    common = len(np.intersect1d(u, v, assume_unique=True))
    return common >= similarity * (len(u) + len(v) - common)


def block_links(nodes: list, sets: list[np.ndarray], similarity: float) -> list[tuple]:
    """Verified links that join what all verified pairs of the sets join: one less than a group has members."""
    root, out = list(range(len(sets))), []

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    have = Sketches([sketch(u) for u in sets], np.array([len(u) for u in sets], np.int64), similarity)
    for j in range(1, len(sets)):
        before = np.arange(j)
        for i in before[have.near(before, np.full(j, j))].tolist():
            a, b = find(i), find(j)
            if a != b and _jaccard_reaches(sets[i], sets[j], similarity):
                root[max(a, b)] = min(a, b)
                out.append((nodes[i], nodes[j]))
    return out


def _families(links: DataFrame, prefixes: DataFrame) -> DataFrame:
    """(node, component, blocks): the components of unverified links, and how many blocks each is cut into."""
    joined = components(links)
    of = joined.join(prefixes.select("node", "size"), "node").groupBy("component").agg(F.count("*").alias("k"), F.sum("size").alias("s"))
    cut = of.select("component", F.greatest(F.ceil(F.col("k") / FAMILY), F.ceil(F.col("s") / FAMILY_SHINGLES), F.lit(1)).cast("int").alias("blocks"))
    return materialize(joined.join(cut, "component").select("node", "component", "blocks"), "families")


def _own_block() -> Column:
    return F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")


def _verify_families(families: DataFrame, one: DataFrame, words: int, similarity: float) -> DataFrame:
    """(a, b): links of the blocks' groups. A family's first document is in each of its blocks."""
    key = ("component", "block")
    everywhere = F.when(F.col("node") == F.col("component"), F.sequence(F.lit(0), F.col("blocks") - 1)).otherwise(F.array(_own_block()))
    sent = one.join(families, "node").select("component", F.explode(everywhere).alias("block"), "node", "text")

    def verify(batches):
        for t in whole_cells(batches, key):
            node, texts = t.column("node").to_numpy(), t.column("text")
            out: list[tuple] = []
            start = starts(t, key)
            for s, e in zip(start.tolist(), [*start[1:].tolist(), len(node)]):
                sets = _sets(texts.slice(s, e - s).combine_chunks(), words)
                out += block_links(node[s:e].tolist(), sets, similarity)
            ends = np.array(out, np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([pa.array(ends[:, 0]), pa.array(ends[:, 1])], ["a", "b"])

    dealt = sent.repartition(*key).sortWithinPartitions(*key, "node")
    return materialize(dealt.mapInArrow(verify, "a long, b long"), "verified")


def _still_apart(cells: DataFrame, prefixes: DataFrame, similarity: float, roots: DataFrame, families: DataFrame, block: int = 2048) -> DataFrame:
    """(a, b): every pair of a cell that the bounds allow, of different roots, that has not met in a block.

    Cells over ``block`` nodes are cut into blocks, which are compared each with each.
    """
    key = ("h", "i", "j")
    known = families.select("node", F.col("component").alias("family"), _own_block().alias("met"))
    rows = cells.join(roots, "node", "left").join(known, "node", "left").select("h", "node", "n", F.coalesce("component", "node").alias("root"), F.coalesce("family", "node").alias("family"), F.coalesce("met", F.lit(0)).alias("met"))
    open_ = rows.groupBy("h").agg(F.min("root").alias("l"), F.max("root").alias("r"), F.min("family").alias("f"), F.max("family").alias("g"), F.max("met").alias("m")).where("l <> r and (f <> g or m > 0)").select("h")
    rows = rows.join(open_, "h", "left_semi").withColumn("by", F.ceil(F.col("n") / block).cast("int")).withColumn("own", F.pmod(F.xxhash64("node"), F.col("by")).cast("int"))
    rows = rows.withColumn("k", F.explode(F.sequence(F.lit(0), F.col("by") - 1))).withColumn("i", F.least("own", "k")).withColumn("j", F.greatest("own", "k"))
    held = prefixes.select("node", "size", "sketch")
    dealt = rows.join(held, "node").select(*key, "own", "node", "root", "family", "met", "size", "sketch").repartition(*key).sortWithinPartitions(*key, "node")

    def compare(batches):
        for t in whole_cells(batches, key):
            start = starts(t, key)
            node, root, family, met, own, i, j = (t.column(c).to_numpy() for c in ("node", "root", "family", "met", "own", "i", "j"))
            have = Sketches(t.column("sketch").to_pylist(), t.column("size").to_numpy(), similarity)
            out = [np.zeros((0, 2), np.int64)]
            for s, e in zip(start.tolist(), [*start[1:].tolist(), len(node)]):
                at = np.arange(s, e)
                left, right = at[own[at] == i[s]], at[own[at] == j[s]]
                some = max(1, AT_ONCE // max(1, len(right)))
                for k in range(0, len(left), some):
                    part = left[k : k + some]
                    apart = (root[part][:, None] != root[right][None, :]) & ((i[s] != j[s]) | (part[:, None] < right[None, :]))
                    apart &= (family[part][:, None] != family[right][None, :]) | (met[part][:, None] != met[right][None, :])
                    x, y = np.nonzero(apart)
                    a, b = part[x], right[y]
                    hit = have.near(a, b)
                    out.append(np.stack([node[a[hit]], node[b[hit]]], 1))
            found = np.unique(np.sort(np.concatenate(out), axis=1), axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(found[:, 0]), pa.array(found[:, 1])], ["a", "b"])

    return materialize(dealt.mapInArrow(compare, "a long, b long").distinct(), "apart")


def _verify_pairs(pairs: DataFrame, one: DataFrame, words: int, similarity: float) -> DataFrame:
    """Of (a, b) those that reach the similarity."""
    asked = pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    texts = materialize(one.join(asked, "node", "left_semi"), "texts")
    left = texts.select(F.col("node").alias("a"), F.col("text").alias("x"))
    right = texts.select(F.col("node").alias("b"), F.col("text").alias("y"))

    def check(batches):
        for t in batches:
            x, y = (t.column(c).cast(pa.large_string()).dictionary_encode() for c in ("x", "y"))
            u, v = (_sets(c.dictionary, words) for c in (x, y))
            keep = [_jaccard_reaches(u[i], v[j], similarity) for i, j in zip(x.indices.to_pylist(), y.indices.to_pylist())]
            yield t.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    met = pairs.join(right, "b").join(left, "a").select("a", "b", "x", "y")
    out = materialize(met.mapInArrow(check, "a long, b long"), "alike")
    discard(texts)
    return out


def groups(df: DataFrame, words: int = 5, similarity: float = 0.8, doc_id: str = "doc_id", text: str = "text", candidates: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """(doc_id, h, kept): every different (id, text) of ``df`` that has an id, h the text's hash, with the least id of its group.

    ``candidates`` makes unverified links (a, b) from different texts (node, text); they join families as those of cells do.
    """
    spark = df.sparkSession
    known = df.where(F.col(f"`{doc_id}`").isNotNull()).select(F.col(f"`{doc_id}`").alias("doc_id"), tx.whole(F.col(f"`{text}`")).alias("text"))
    hashes = known.select("doc_id", F.xxhash64("text").alias("h1"), F.xxhash64(F.lit(1), "text").alias("h2"))
    hashes = materialize(hashes.groupBy("doc_id", "h1", "h2").agg(F.count("*").alias("rows")), "hashes")
    size = hashes.groupBy("doc_id").agg(F.count("*").alias("texts"), F.sum("rows").alias("rows")).agg(F.count("*").alias("ids"), F.sum("texts").alias("texts"), F.sum("rows").alias("rows")).first()
    whole = dict(known.dtypes)["doc_id"] in ("bigint", "int", "smallint", "tinyint") and size["ids"] == (size["texts"] or 0)
    # a document is named by its id; by a hash where ids are no integers or an id has several texts
    name = lambda h1, h2: F.col("doc_id").cast("long") if whole else F.xxhash64("doc_id", h1, h2)
    classes = hashes.withColumn("node", name(F.col("h1"), F.col("h2"))).groupBy("h1", "h2").agg(F.min("node").alias("class"), F.count("*").alias("n"))
    classes = materialize(classes, "classes")
    one = known.select(name(F.xxhash64("text"), F.xxhash64(F.lit(1), "text")).alias("node"), "text")
    if size["rows"] != size["texts"]:
        one = one.dropDuplicates(["node"])
    firsts = classes.select(F.col("class").alias("node"))
    prefixes = materialize(_prefixes(one, words, similarity, size["texts"] or 0).join(firsts, "node", "left_semi"), "prefixes")
    release(spark)
    cells = _cells(prefixes)
    release(spark)
    unverified = _links_of_cells(cells, prefixes, similarity)
    if candidates is not None:
        unverified = unverified.union(candidates(one.join(firsts, "node", "left_semi"))).distinct()
    families = _families(unverified, prefixes)
    release(spark)
    links = _verify_families(families, one, words, similarity)
    release(spark)
    pairs = _still_apart(cells, prefixes, similarity, components(links), families)
    discard(cells, prefixes, families)
    release(spark)
    joined = components(links.union(_verify_pairs(pairs, one, words, similarity)))
    label = meet(hashes, classes, ["h1", "h2"], "n").join(joined, F.col("class") == F.col("node"), "left")
    label = materialize(label.select("doc_id", F.col("h1").alias("h"), F.coalesce("component", "class").alias("group")), "groups")
    discard(hashes, classes)
    if whole:  # a group is called by its least id
        return label.select("doc_id", "h", F.col("group").cast(label.schema["doc_id"].dataType).alias("kept"))
    least = materialize(label.groupBy("group").agg(F.min("doc_id").alias("kept"), F.count("*").alias("n")), "least")
    return meet(label, least, ["group"], "n").select("doc_id", "h", "kept")
