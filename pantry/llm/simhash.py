"""SimHash near-duplicates by anchor points of a covering code.

Fingerprints are cut into three blocks of 22, 21 and 21 bits. Two fingerprints that differ in at most
t bits differ in at most t // 3 of some block, so each block is an index of its own. Inside a block the
anchors are the words of the perfect binary Golay code of length 23 (the block padded with zeros): every
block value lies within 3 bits, the covering radius, of exactly one anchor, its home. A fingerprint is
replicated to every anchor within 3 + t // 3 bits, so that it meets, at the home of any partner, that
partner; homes are then compared with all that came to the anchor, over all 64 bits.

Equal fingerprints are one row from the start, so copies, however many, cost nothing here. An anchor's
task emits a spanning forest of the links it sees, not the pairs; anchors that draw more than ``block``
rows are cut into a grid of blocks that together compare the same rows. Components are then joined by
star rounds. Links between different fingerprints are all found: the cover is exact.

One block's anchors are a fixed number, so each fingerprint meets a fixed share (0.4 % at t = 4) of all. From
``JOINT`` fingerprints on, the index is therefore of two blocks together: of any three numbers of differing bits
the two least add up to 2 t // 3 at most, so a fingerprint goes to the pairs of anchors that exceed the covering
radius by that much in all. It has more replicas (about 180) and meets a share of 0.001 %; the links are the same.

Defined results: fewer than ``shingle`` words are one shingle; null and empty texts have fingerprint 0,
linked like any other; rows that repeat or lack an id count as they are (null ids form a component
label only where no id is at hand); an empty table gives an empty result.
"""

from __future__ import annotations

import functools
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pantry.llm import text as tx
from pantry.llm.components import components
from pantry.llm.ranks import meet
from pantry.session import materialize

#: Generator polynomial of the binary Golay code, block starts and widths.
GOLAY = 0b101011100011
BLOCKS = ((0, 22), (22, 21), (43, 21))
RADIUS = 3
#: Different fingerprints from which on the replicas of two blocks cost less than the comparisons of one.
JOINT = 1 << 25
#: Comparisons held in memory at once.
AT_ONCE = 1 << 21


def shingles(text: str | None, shingle: int, seed: int) -> np.ndarray:
    """XXH64 of the text's word shingles, repeats included; of the whole sequence if it is shorter."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    h = xxhash.xxh64_intdigest
    joined = b" ".join(words)
    if len(words) <= shingle:
        return np.array([h(joined, seed)] if words else [], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    n = len(words) - shingle + 1
    return np.fromiter((h(joined[a:b], seed) for a, b in zip(starts[:n].tolist(), ends[shingle - 1 :].tolist())), np.uint64, n)


def fingerprint(text: str | None, shingle: int = 4, seed: int = 42, once: bool = False) -> int:
    """SimHash of one text: a bit is set if it is in over half of the shingles' hashes (``once``: of the different ones)."""
    hashes = shingles(text, shingle, seed)
    if once:
        hashes = np.unique(hashes)
    n = len(hashes)
    counts = np.zeros(64, np.int64)
    for i in range(0, n, 1 << 16):
        counts += np.unpackbits(hashes[i : i + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * counts > n, bitorder="little").view("<u8")[0])


def fingerprints(df: DataFrame, shingle: int = 4, seed: int = 42, once: bool = False, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed long."""

    def run(batches):
        for b in batches:
            fp = np.fromiter((fingerprint(t, shingle, seed, once) for t in b.column(1).to_pylist()), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp.view(np.int64))], ["doc_id", "fp"])

    slim = df.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    return slim.mapInArrow(run, f"doc_id {dict(slim.dtypes)['doc_id']}, fp long")


def _remainder(v: np.ndarray) -> np.ndarray:
    """Remainders of 23-bit values by the generator: 0 for code words."""
    v = v.copy()
    for bit in range(22, 10, -1):
        v ^= np.where((v >> bit) & 1, GOLAY << (bit - 11), 0)
    return v


@functools.cache
def _errors(radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Error patterns up to ``radius`` bits in order of remainder and weight, where each remainder's begin, and their numbers."""
    patterns = np.array([sum(1 << i for i in c) for w in range(radius + 1) for c in combinations(range(23), w)], np.int64)
    order = np.argsort(rem := _remainder(patterns), kind="stable")
    n = np.bincount(rem, minlength=2048)
    return patterns[order], np.concatenate([[0], np.cumsum(n)[:-1]]), n


def anchors(values: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, anchor) for every code word within ``radius`` bits; each row's home comes first."""
    patterns, begin, n = _errors(radius)
    rem = _remainder(values)
    row = np.repeat(np.arange(len(values)), n[rem])
    place = np.arange(len(row)) - np.repeat(np.cumsum(n[rem]) - n[rem], n[rem])
    return row, values[row] ^ patterns[begin[rem][row] + place]


def _replicas(fp: np.ndarray, bits: int, joint: bool):
    """(anchor, row, home) for each index: every anchor a fingerprint is sent to, and whether it is its home."""
    budget = bits * 2 // len(BLOCKS) if joint else bits // len(BLOCKS)
    near = []
    for start, width in BLOCKS:
        value = ((fp >> np.uint64(start)) & np.uint64((1 << width) - 1)).astype(np.int64)
        row, word = anchors(value, RADIUS + budget)
        near.append((row, word, np.maximum(np.bitwise_count(value[row] ^ word).astype(np.int64) - RADIUS, 0)))
    if not joint:
        for k, (row, word, over) in enumerate(near):
            yield (k << 23) | word, row, over == 0  # the code is perfect: one word is within its radius
        return
    for k, (a, b) in enumerate(combinations(range(len(BLOCKS)), 2)):
        (row, word, over), (row2, word2, over2) = near[a], near[b]
        for spent in range(budget + 1):
            mine, theirs = over == spent, over2 <= budget - spent
            r, w, r2 = row[mine], word[mine], row2[theirs]
            n = np.bincount(r2, minlength=len(fp))
            first = np.cumsum(n) - n
            i = np.repeat(np.arange(len(r)), n[r])
            j = first[r][i] + np.arange(len(i)) - np.repeat(np.cumsum(n[r]) - n[r], n[r])
            yield (k << 46) | (w[i] << 23) | word2[theirs][j], r[i], over2[theirs][j] + spent == 0


def _hung(parent: np.ndarray, child: np.ndarray, bits: int) -> list[tuple[int, int]]:
    """Links of the same reach through the least child of each parent where that is near enough: a group that
    meets at many anchors then names the same links at most of them, and they are one row after ``distinct``."""
    if not len(parent):
        return []
    order = np.argsort(parent, kind="stable")
    parent, child = parent[order], child[order]
    first = np.flatnonzero(np.concatenate([[True], parent[1:] != parent[:-1]]))
    hub = np.repeat(np.minimum.reduceat(child, first), np.diff([*first, len(parent)]))
    near = (np.bitwise_count(hub ^ child) <= bits) & (hub != child)
    return list(zip(np.where(near, hub, parent).tolist(), child.tolist()))


def forest(home: np.ndarray, others: np.ndarray, bits: int) -> list[tuple[int, int]]:
    """Links that connect what home x others within ``bits`` connects: at most one a row.

    From each home not reached yet the search spreads over rows not reached yet, so a dense group is
    scanned about once for each home it holds, and its pairs are never listed.
    """
    out: list[tuple[int, int]] = []
    rest, homes = others.copy(), home.copy()
    front = homes[:0]
    while len(homes) or len(front):
        if not len(front):
            front, homes = homes[:1], homes[1:]
        some = max(1, AT_ONCE // max(1, len(rest)))
        now, front = front[:some], front[some:]
        near = np.bitwise_count(now[:, None] ^ rest[None, :]) <= bits
        hit = near.any(0)
        out += _hung(now[near.argmax(0)[hit]], rest[hit], bits)
        reached, rest = rest[hit], rest[~hit]
        some = max(1, AT_ONCE // max(1, len(homes)))
        for i in range(0, len(reached), some):  # homes that a reached row touches belong too and search on
            part = reached[i : i + some]
            back = np.bitwise_count(homes[:, None] ^ part[None, :]) <= bits
            joins = back.any(1)
            out += zip(homes[joins].tolist(), part[back.argmax(1)[joins]].tolist())
            front, homes = np.concatenate([front, homes[joins]]), homes[~joins]
    return [(a, b) for a, b in out if a != b]


def links(distinct: DataFrame, bits: int = 4, block: int = 8192, joint: bool | None = None) -> DataFrame:
    """(a, b): fingerprints that differ in at most ``bits`` bits, enough of them to keep all components.

    ``joint`` indexes two blocks together; unset, their number decides. Both find the same components.
    """
    joint = distinct.count() >= JOINT if joint is None else joint

    def replicate(parts):
        for t in parts:
            fp = t["fp"].to_numpy().view(np.uint64)
            for anchor, row, home in _replicas(fp, bits, joint):
                yield pd.DataFrame({"anchor": anchor, "fp": t["fp"].to_numpy()[row], "home": home})

    sent = materialize(distinct.select("fp").mapInPandas(replicate, "anchor long, fp long, home boolean"), "anchors")
    sizes = sent.groupBy("anchor").agg(F.count("*").alias("n"), F.sum(F.col("home").cast("long")).alias("homes")).where("homes > 0 and n > 1")
    cut = sizes.select("anchor", F.ceil(F.col("n") / block).cast("int").alias("by"), F.ceil(F.col("homes") / block).cast("int").alias("hy"))
    met = sent.join(cut, "anchor")
    spread = lambda rows, own, of, other: rows.withColumn(own, F.pmod(F.xxhash64("fp"), F.col(of)).cast("int")).withColumn(other, F.explode(F.sequence(F.lit(0), F.col({"hy": "by", "by": "hy"}[of]) - 1)))
    homes = spread(met.where("home"), "i", "hy", "j").withColumn("side", F.lit(True))
    others = spread(met, "j", "by", "i").withColumn("side", F.lit(False))
    cells = homes.select("anchor", "i", "j", "side", "fp").unionByName(others.select("anchor", "i", "j", "side", "fp"))
    dealt = cells.repartition("anchor", "i", "j").sortWithinPartitions("anchor", "i", "j")

    def compare(batches):
        held: list[pa.RecordBatch] = []

        def solved(t: pa.Table):
            key = [t.column(c).to_numpy() for c in ("anchor", "i", "j")]
            fp, side = t.column("fp").to_numpy().view(np.uint64), t.column("side").to_numpy()
            new = np.flatnonzero(np.logical_or.reduce([k[1:] != k[:-1] for k in key])) + 1
            found = []
            for a, b in zip([0, *new.tolist()], [*new.tolist(), len(fp)]):
                home, others_ = fp[a:b][side[a:b]], fp[a:b][~side[a:b]]
                if len(home) and len(others_):
                    found += forest(home, others_, bits)
            ends = np.array(found, np.uint64).reshape(-1, 2).view(np.int64)
            return pa.RecordBatch.from_arrays([pa.array(ends[:, 0]), pa.array(ends[:, 1])], ["a", "b"])

        for b in batches:  # whole cells at a time: the last one of a batch may go on in the next
            if not b.num_rows:
                continue
            held.append(b)
            t = pa.Table.from_batches(held)
            key = [t.column(c).to_numpy() for c in ("anchor", "i", "j")]
            open_ = np.logical_and.reduce([k == k[-1] for k in key])
            at = int(np.flatnonzero(open_)[0])
            if at:
                yield solved(t.slice(0, at))
            held = t.slice(at).combine_chunks().to_batches()
        if held:
            yield solved(pa.Table.from_batches(held))

    return dealt.mapInArrow(compare, "a long, b long").distinct()


def near_duplicates(df: DataFrame, bits: int = 4, shingle: int = 4, seed: int = 42, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row; the label is the least doc_id reachable."""
    prints = materialize(fingerprints(df, shingle, seed, False, doc_id, text), "prints")
    distinct = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("n")), "classes")
    joined = components(links(distinct, bits))
    rooted = distinct.join(joined, F.col("fp") == F.col("node"), "left").select("fp", "least", "n", F.coalesce("component", "fp").alias("root"))
    rooted = materialize(rooted, "rooted")
    label = materialize(rooted.groupBy("root").agg(F.min("least").alias("component_id"), F.count("*").alias("k")), "labels")
    known = materialize(meet(rooted, label, ["root"], "k").select("fp", "component_id", "n"), "known")
    out = meet(prints, known, ["fp"], "n")
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def candidate_links(texts: DataFrame, words: int = 5, bits: int = 4) -> DataFrame:
    """(a, b): links of (node, text) by fingerprints, enough of them to keep all components."""
    prints = materialize(fingerprints(texts, words, once=True, doc_id="node"), "prints")
    distinct = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("first"), F.count("*").alias("n")), "classes")
    equal = meet(prints, distinct, ["fp"], "n").where("doc_id <> first").select(F.col("first").alias("a"), F.col("doc_id").alias("b"))
    name = lambda end: distinct.select(F.col("fp").alias(end), F.col("first").alias(f"{end}_node"))
    near = links(distinct, bits).join(name("a"), "a").join(name("b"), "b").select(F.col("a_node").alias("a"), F.col("b_node").alias("b"))
    return materialize(equal.union(near), "near")


def keep_one(df: DataFrame, words: int = 5, similarity: float = 0.8, doc_id: str = "doc_id", text: str = "text", bits: int = 4) -> DataFrame:
    """The rows of ``df``, one of each group of near-duplicates: that with the least doc_id.

    Fingerprints of five-word shingles that differ in at most ``bits`` bits link texts; the components of these links are
    verified text by text: a pair counts if the Jaccard similarity of its sets of shingles is 0.8 or more, and groups
    are the components of such pairs. Fingerprints of 64 bits cannot find all of them (a header of a quarter of the
    text moves nine bits or more), so the rest comes from shared shingles: see ``similar.groups``, which misses none.
    Rows without an id stay; rows that repeat a kept id stay; ids may be numbers or strings.
    """
    from pantry.llm import similar

    lost, same = tx.fresh(df, "lost", "same")
    gone = similar.groups(df, words, similarity, doc_id, text, lambda texts: candidate_links(texts, words, bits)).where("doc_id <> kept").select(F.col("doc_id").alias(lost), F.col("h").alias(same))
    return df.join(gone, (F.col(f"`{doc_id}`") == F.col(lost)) & (F.xxhash64(tx.whole(F.col(f"`{text}`"))) == F.col(same)), "left_anti")
