"""SimHash near-dedup by a self-join of binary tries.

A document's fingerprint has bit b set if b is set in over half of the XXH64 values of its word shingles. Two
fingerprints are linked if they differ in at most `budget` bits; the classes are the connected components.

Equal fingerprints are merged first, so copies cost nothing more. Two fingerprints within the budget agree on all but `budget`
of `BLOCKS` bit blocks, so each fingerprint goes, once for each choice of blocks to agree on, to the group of those
that share these bits. With 6 blocks and 2 errors a fingerprint goes to 15 groups with 42 or 43 bits fixed, so no
group can have more than 2^22 members, whatever the data: one task holds any of them. Within a group the sorted
fingerprints are a binary trie, whose nodes are ranges. Pairs of nodes are followed down together, level by level; the bits in
which they differ add up, and a pair goes as soon as they exceed the budget. From each group only a spanning forest of
the links leaves, so a class of n members makes at most n rows a group and never n squared.

Two bits are too few for near copies: texts that share 0.8 of their five-word shingles differ in 4 to 13 of 64 bits. `wide_pairs`
finds these, for the stage of the pipeline. It has WIDE fingerprints of a text, from the same shingles with other hashes. In a group
agree the 21 bits of one third of one fingerprint, and its trie is followed with a budget of 14 bits; a pair has to hold on the first
fingerprint too (28 of 128 bits), and the pairs' five-word shingles are compared in full. Pairs whose sizes and parities of shingles show that they
are no near copies are left out. This is done twice. First each group of a few fingerprints gives a chain of neighbours and a star around its
most typical member, and what these comparisons link is one class in the second search, so a class of very many different near copies isn't compared
pair by pair. Then come all pairs between classes, each from the first third that it agrees on.

Defined results: a null or empty text has fingerprint 0 and is linked like any other; fewer words than a shingle has
are one shingle; a null doc_id takes part but never names a class that has another id; repeated rows each get a row;
an empty table gives an empty table; extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import chain, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from farfield.llm.classes import classes_of_links
from farfield.llm.common import DOCUMENT_COLUMNS, let_workers_import, looked_up, slices, written

SHINGLE_WORDS = 3
BUDGET = 2
BLOCKS = 6
SEED = 42
#: For the stage: shingle words and similarity of near copies, fingerprints of a text, thirds of each to agree on, bits that may differ.
NEAR_WORDS, NEAR = 5, 0.8
WIDE = 24
THIRDS = 3
WIDE_BUDGET, PAIR_BUDGET = 14, 28
#: Longs of a shingle set's sketch.
ODD = 4
#: Fingerprints whose groups are searched first.
FIRST = 4
#: Node pairs that are followed down at once.
FRONT = 1 << 20


def _odd(k: int) -> np.uint64:
    """The multiplier of the k-th fingerprint's hash."""
    return np.uint64(xxhash.xxh64_intdigest(k.to_bytes(8, "big"), SEED) | 1)


def wide_fingerprint(text: str | None, words: int = SHINGLE_WORDS, count: int = 1) -> np.ndarray:
    """`count` fingerprints, unsigned; the first is that of the XXH64 values themselves, the others are of these values mixed again.
    bytes.lower and bytes.split know ASCII only: just the letters and white space meant."""
    w = (text or "").encode().lower().split()
    if not w:
        return np.zeros(count, np.uint64)
    n = max(1, len(w) - words + 1)
    digest = xxhash.xxh64_intdigest
    over = np.zeros(64 * count, np.int64)
    step = 8 * 255
    for at in range(0, n, step):  # whole texts of any length in bounded memory
        part = w[at : at + step + words - 1]
        if n == 1:
            h = [digest(b" ".join(part), SEED)]
        else:
            h = [digest(s, SEED) for s in map(b" ".join, zip(*(part[k:] for k in range(words))))]
        h = np.array(h, np.uint64)
        rows = -(-len(h) // 255) * 255
        all_ = np.zeros((rows, count), ">u8")
        all_[: len(h), 0] = h
        for k in range(1, count):
            x = h * _odd(k)
            x = (x ^ (x >> np.uint64(32))) * _odd(-k % (1 << 32))
            all_[: len(h), k] = x ^ (x >> np.uint64(29))
        bits = np.unpackbits(all_.view(np.uint8).reshape(rows, 8 * count), axis=1)
        over += bits.reshape(-1, 255, 64 * count).sum(axis=1, dtype=np.uint8).sum(axis=0, dtype=np.int64)
    return np.packbits(over * 2 > n).view(">u8").astype(np.uint64)


def fingerprint(text: str | None, words: int = SHINGLE_WORDS) -> int:
    """As an unsigned number."""
    return int(wide_fingerprint(text, words)[0])


def fingerprints(docs: DataFrame, words: int = SHINGLE_WORDS, count: int = 1, sketch: bool = False) -> DataFrame:
    """(doc_id, fp, wide): fp as a signed long with the same bits, wide all `count` of them. If sketch, also sketch: shingle_sketch of the text."""
    let_workers_import(docs.sparkSession)

    def lists(x: np.ndarray) -> pa.ListArray:
        return pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), pa.array(x.ravel()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            fps = np.array([wide_fingerprint(t.as_py(), words, count) for t in batch.column(1)], np.uint64).reshape(-1, count).view(np.int64)
            out = [batch.column(0), pa.array(np.ascontiguousarray(fps[:, 0])), lists(fps)]
            if sketch:
                out.append(lists(np.array([shingle_sketch(t.as_py()) for t in batch.column(1)], np.int64).reshape(-1, 1 + ODD)))
            yield pa.RecordBatch.from_arrays(out, names=["doc_id", "fp", "wide", "sketch"][: len(out)])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, fp long, wide array<long>" + sketch * ", sketch array<long>")


def block_masks(budget: int = BUDGET, blocks: int = BLOCKS) -> list[int]:
    """The bits to agree on, for each choice of the blocks that may differ."""
    edges = [round(64 * k / blocks) for k in range(blocks + 1)]
    block = [((1 << (b - a)) - 1) << a for a, b in zip(edges, edges[1:])]
    return [sum(c) for c in combinations(block, blocks - budget)]


def trie_pairs(fps: np.ndarray, starts: np.ndarray, ends: np.ndarray, budget: int, cls: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of places in fps whose numbers differ in at most budget bits, within each range [start, end) that is sorted and free
    of repeats. A node is a range, a pair of nodes two of them and the bits in which they differ so far. With classes of the places,
    only pairs between different ones: a pair of nodes goes if all their members are of one class."""
    run = None if cls is None else np.concatenate([[0], np.cumsum(cls[1:] != cls[:-1]), [-1]])
    stack = [(63, starts, ends, starts, ends, np.zeros(len(starts), np.int8))]
    ones: dict[int, np.ndarray] = {}

    def upto(bit: int) -> np.ndarray:
        if bit not in ones:
            ones[bit] = np.concatenate([[0], np.cumsum((fps >> np.uint64(bit)) & np.uint64(1), dtype=np.int64)])
        return ones[bit]

    while stack:
        bit, al, ah, bl, bh, off = stack.pop()
        if len(al) > FRONT and bit >= 0:
            half = len(al) // 2
            stack += [(bit, *(x[s] for x in (al, ah, bl, bh, off))) for s in (slice(half), slice(half, None))]
            continue
        if bit < 0:
            if len(al):
                yield al, bl
            continue
        c = upto(bit)
        am, bm = ah - (c[ah] - c[al]), bh - (c[bh] - c[bl])
        same = al == bl
        kids = [
            (al, am, bl, bm, off, np.ones(len(al), bool)),
            (am, ah, bm, bh, off, np.ones(len(al), bool)),
            (al, am, bm, bh, off + 1, off < budget),
            (am, ah, bl, bm, off + 1, (off < budget) & ~same),
        ]
        nxt = []
        for xl, xh, yl, yh, o, ok in kids:
            # a node paired with itself needs two members, two nodes need one each
            ok = ok & (xh > xl) & (yh > yl) & ~((xl == yl) & (xh - xl < 2))
            if run is not None:
                at, bt = np.where(ok, xl, 0), np.where(ok, yl, 0)
                ok = ok & ~((run[at] == run[xh - 1]) & (run[bt] == run[yh - 1]) & (cls[at] == cls[bt]))
            nxt.append([v[ok] for v in (xl, xh, yl, yh, o)])
        stack.append((bit - 1, *(np.concatenate(v) for v in zip(*nxt))))


class Forest:
    """Least member of each class of 0..n-1, under links that come in batches."""

    def __init__(self, n: int):
        self.least = np.arange(n)

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        least = self.least
        while True:
            x, y = least[a], least[b]
            if (x == y).all():
                break
            low, high = np.minimum(x, y), np.maximum(x, y)
            np.minimum.at(least, high, low)
            while not (least == (up := least[least])).all():
                least[:] = up


def _links_of_groups(budget: int):
    def of(mask_no: np.ndarray, key: np.ndarray, fp: np.ndarray) -> pa.RecordBatch:
        new = np.flatnonzero(np.concatenate([[True], (mask_no[1:] != mask_no[:-1]) | (key[1:] != key[:-1])]))
        end = np.append(new[1:], len(fp))
        many = end - new > 1
        forest = Forest(len(fp))
        for a, b in trie_pairs(fp, new[many], end[many], budget):
            forest.link(a, b)
        at = np.flatnonzero(forest.least != np.arange(len(fp)))
        return pa.RecordBatch.from_arrays(
            [pa.array(fp[at].view(np.int64)), pa.array(fp[forest.least[at]].view(np.int64))], names=["a", "b"]
        )

    return lambda batches: _whole_groups(batches, of)


def _whole_groups(batches: Iterator[pa.RecordBatch], of) -> Iterator[pa.RecordBatch]:
    """`of` on runs of whole groups; rows come sorted by the first two columns, which name the group. The others are longs."""
    rest = None
    for batch in batches:
        got = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
        got[2] = got[2].view(np.uint64)
        if rest is not None:
            got = [np.concatenate(x) for x in zip(rest, got)]
        if not len(got[0]):
            continue
        # the last group may go on in the next batch
        cut = len(got[0]) - int(np.argmax((got[0][::-1] != got[0][-1]) | (got[1][::-1] != got[1][-1])))
        cut = 0 if (got[0][0] == got[0][-1] and got[1][0] == got[1][-1]) else cut
        if cut:
            yield of(*(x[:cut] for x in got))
        rest = [x[cut:] for x in got]
    if rest is not None and len(rest[0]):
        yield of(*rest)


def _every_pair_of_groups(budget: int, pair_budget: int):
    def of(mask_no: np.ndarray, key: np.ndarray, fp: np.ndarray, other: np.ndarray, doc: np.ndarray, cls: np.ndarray, *sketch: np.ndarray) -> Iterator[pa.RecordBatch]:
        new, end = _bounds(mask_no, key)
        many = end - new > 1
        for a, b in every_member_pair(fp, new[many], end[many], budget, cls):
            near = _near(fp, other, cls, sketch, a, b, pair_budget)[1] & _first_third(mask_no[a], fp[a] ^ fp[b])
            if near.any():
                yield _pairs(doc, cls, a[near], b[near])

    return lambda batches: chain.from_iterable(_whole_groups(batches, of))


def _first_third(mask_no: np.ndarray, differ: np.ndarray) -> np.ndarray:
    """Whether a pair agrees on no third of the fingerprint before the one that its group goes by. A pair that agrees on several is in the groups of all of
    them, and each of them finds it, so that of the first is enough."""
    own, seen = mask_no % THIRDS, np.zeros(len(mask_no), bool)
    for t in range(THIRDS - 1):
        seen |= (t < own) & (differ & np.uint64(0x1FFFFF << (21 * t)) == 0)
    return ~seen


def _bounds(mask_no: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    new = np.flatnonzero(np.concatenate([[True], (mask_no[1:] != mask_no[:-1]) | (key[1:] != key[:-1])]))
    return new, np.append(new[1:], len(key))


def _near(fp: np.ndarray, other: np.ndarray, cls: np.ndarray, sketch: tuple[np.ndarray, ...], a: np.ndarray, b: np.ndarray, pair_budget: int) -> tuple[np.ndarray, np.ndarray]:
    """Bits in which the other fingerprints differ, and whether a pair is near and between classes and can be one of near copies."""
    off = np.bitwise_count((other[a] ^ other[b]).view(np.uint64)).astype(np.int64)
    return off, (np.bitwise_count(fp[a] ^ fp[b]) + off <= pair_budget) & (cls[a] != cls[b]) & can_be_near(sketch, a, b)


def can_be_near(sketch: tuple[np.ndarray, ...], a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """False only for pairs whose similarity is below NEAR for sure: the shingles that only one of two texts has are at least as
    many as the bits in which the parities differ, and as the sizes do."""
    size, *odd = sketch
    lone = np.abs(size[a] - size[b])
    if odd:
        lone = np.maximum(lone, sum(np.bitwise_count((x[a] ^ x[b]).view(np.uint64)).astype(np.int64) for x in odd))
    return lone * (1 + NEAR) <= (size[a] + size[b]) * (1 - NEAR) + 1e-6


def _pairs(doc: np.ndarray, cls: np.ndarray, a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    low, high = np.where(doc[a] < doc[b], a, b), np.where(doc[a] < doc[b], b, a)
    return pa.RecordBatch.from_arrays([pa.array(x) for x in (doc[low], doc[high], cls[low], cls[high])], names=["a", "b", "ca", "cb"])


def chain_and_star(fp: np.ndarray, new: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs within each range [new, end), fewer than twice its members: each with the next, and all with the one that is nearest to the majority of each bit."""
    group = np.repeat(np.arange(len(new)), end - new)
    ones = np.add.reduceat(np.unpackbits(fp.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1), new, axis=0, dtype=np.int64)
    typical = np.packbits(ones * 2 > (end - new)[:, None], axis=1).view(">u8").ravel().astype(np.uint64)
    places = np.arange(len(fp))
    order = np.bitwise_count(fp ^ typical[group]).astype(np.int64) * len(fp) + places
    middle = (np.minimum.reduceat(order, new) % len(fp))[group]
    next_ = np.flatnonzero(group[1:] == group[:-1])
    spoke = np.flatnonzero(middle != places)
    return np.concatenate([next_, middle[spoke]]), np.concatenate([next_ + 1, spoke])


def _first_pairs_of_groups(pair_budget: int):
    def of(mask_no: np.ndarray, key: np.ndarray, fp: np.ndarray, other: np.ndarray, doc: np.ndarray, cls: np.ndarray, *sketch: np.ndarray) -> pa.RecordBatch:
        a, b = chain_and_star(fp, *_bounds(mask_no, key))
        near = _near(fp, other, cls, sketch, a, b, pair_budget)[1]
        return _pairs(doc, cls, a[near], b[near])

    return lambda batches: _whole_groups(batches, of)


def every_member_pair(fp: np.ndarray, starts: np.ndarray, ends: np.ndarray, budget: int, cls: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """As trie_pairs, where members may share a fingerprint: all pairs of all members whose classes may differ, a bounded number at once."""
    at = np.concatenate([np.arange(s, e) for s, e in zip(starts, ends)]) if len(starts) else np.zeros(0, np.int64)
    if not len(at):
        return
    head = np.ones(len(at), bool)
    head[1:] = (fp[at[1:]] != fp[at[:-1]]) | np.isin(at[1:], starts)
    first = np.flatnonzero(head)
    heads, n = at[first], np.diff(np.append(first, len(at)))
    # members of a fingerprint are in one class, or else in none that a trie may leave out
    one = np.minimum.reduceat(cls[at], first) == np.maximum.reduceat(cls[at], first)
    _, of_class = np.unique(cls[heads], return_inverse=True)
    of_class = np.where(one, of_class, -1 - np.arange(len(heads)))
    lo = np.searchsorted(heads, starts)
    mixed = np.flatnonzero(~one)
    tries = trie_pairs(fp[heads], lo, np.append(lo[1:], len(heads)), budget, of_class)
    for x, y in chain([(mixed, mixed)], tries):
        for of, left in _repeated(n[x]):
            a, yo = heads[x[of]] + left, y[of]
            for of2, right in _repeated(n[yo]):
                b = heads[yo[of2]] + right
                ok = (a[of2] < b) & (cls[a[of2]] != cls[b])
                yield a[of2][ok], b[ok]


def _repeated(n: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(k, j) for each k and 0 <= j < n[k], in parts of FRONT or the largest n."""
    done, sums = 0, np.cumsum(n)
    while done < len(n):
        upto = max(done + 1, int(np.searchsorted(sums, (sums[done - 1] if done else 0) + FRONT, side="right")))
        k = np.repeat(np.arange(done, upto), n[done:upto])
        yield k, np.arange(len(k)) - np.repeat(np.cumsum(n[done:upto]) - n[done:upto], n[done:upto])
        done = upto


def links(reps: DataFrame, budget: int = BUDGET, blocks: int = BLOCKS) -> DataFrame:
    """(a, b): links among the distinct fingerprints in reps.fp that leave the same classes as all of them."""
    let_workers_import(reps.sparkSession)
    masks = block_masks(budget, blocks)
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    choices = F.array(*(F.struct(F.lit(k).alias("m"), F.col("fp").bitwiseAND(F.lit(signed(m)).cast("long")).alias("key")) for k, m in enumerate(masks)))
    # The sign bit would put the upper half of the numbers first within a group; flipped, signed order is trie order.
    groups = reps.select("fp", F.explode(choices).alias("g")).select("g.m", "g.key", "fp", F.expr("fp ^ (-9223372036854775807L - 1)").alias("o"))
    return groups.repartition("m", "key").sortWithinPartitions("m", "key", "o").select("m", "key", "fp").mapInArrow(_links_of_groups(budget), "a long, b long")


def wide_pairs(nodes: DataFrame, count: int = WIDE, first: bool = False) -> DataFrame:
    """(a, b, ca, cb), a < b: pairs of nodes.doc whose wide fingerprints are near and whose nodes.cls differ, with these: all of them, or if first the
    chains and stars of the groups."""
    let_workers_import(nodes.sparkSession)
    choices = F.array(*(
        F.struct(F.lit(THIRDS * k + j).alias("m"), F.get("wide", F.lit(k)).alias("fp"), F.get("wide", F.lit(int(k == 0))).alias("other"))
        for k in range(count) for j in range(THIRDS)
    ))
    sketch = [F.get("sketch", F.lit(k)).alias(f"s{k}") for k in range(1 + ODD)]
    rows = nodes.select("doc", "cls", "sketch", F.explode(choices).alias("g")).select("g.m", "g.fp", "g.other", "doc", "cls", *sketch)
    # What follows from m and fp is computed on both sides of the shuffle, not carried through it.
    key, order = F.expr(f"fp & shiftleft(2097151L, 21 * (m % {THIRDS}))"), F.expr("fp ^ (-9223372036854775807L - 1)")
    sorted_ = rows.repartition("m", key).sortWithinPartitions("m", key, order).select("m", key.alias("key"), "fp", "other", "doc", "cls", *(f"s{k}" for k in range(1 + ODD)))
    of_groups = _first_pairs_of_groups(PAIR_BUDGET) if first else _every_pair_of_groups(WIDE_BUDGET, PAIR_BUDGET)
    return sorted_.mapInArrow(of_groups, "a long, b long, ca long, cb long").distinct()


def shingle_set(text: str | None, words: int = NEAR_WORDS) -> set[int]:
    w = (text or "").encode().lower().split()
    return {xxhash.xxh64_intdigest(b" ".join(w[k : k + words]), SEED) for k in range(max(1, len(w) - words + 1))} if w else set()


def shingle_sketch(text: str | None) -> list[int]:
    """The number of a text's five-word shingles, and 64 * ODD bits: how many of them fall to each, odd or even."""
    own = shingle_set(text)
    n = np.bincount(np.fromiter(own, np.uint64, len(own)).astype(np.int64) & (64 * ODD - 1), minlength=64 * ODD)
    return [len(own), *np.packbits((n & 1).astype(np.uint8)).view(np.int64).tolist()]


def similarity(a: str | None, b: str | None) -> float:
    """Jaccard similarity of the five-word shingles; that of two texts without words is 1."""
    x, y = shingle_set(a), shingle_set(b)
    return len(x & y) / len(x | y) if x or y else 1.0


def near_copies(pairs: DataFrame, docs: DataFrame, least: float = NEAR) -> DataFrame:
    """Those of the pairs (a, b and more columns) whose texts are at least so similar."""
    text = lambda k, t: docs.select(F.col("doc_id").cast("long").alias(k), F.col("text").cast("string").alias(t))
    schema = T.StructType([*pairs.schema.fields, T.StructField("near", T.BooleanType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, 16):
            near = [similarity(x.as_py(), y.as_py()) >= least for x, y in zip(batch.column("ta"), batch.column("tb"))]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-2], pa.array(near, pa.bool_())], names=[*batch.schema.names[:-2], "near"])

    names = pairs.columns
    both = pairs.join(text("a", "ta"), "a").join(text("b", "tb"), "b").select(*names, "ta", "tb")
    return both.mapInArrow(run, schema).filter("near").select(*names)


def near_classes(docs: DataFrame, words: int = SHINGLE_WORDS, budget: int = BUDGET, blocks: int = BLOCKS) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (least doc_id of the class)."""
    return _classes(written(fingerprints(docs, words).drop("wide"), "fingerprints"), budget, blocks)


def _classes(fps: DataFrame, budget: int, blocks: int) -> DataFrame:
    reps = fps.groupBy("fp").agg(F.min("doc_id").alias("doc"))
    roots = classes_of_links(links(reps, budget, blocks))
    named = reps.join(roots, reps["fp"] == roots["node"], "left").select("fp", "doc", F.coalesce("root", "fp").alias("root"))
    least = named.groupBy(F.col("root").alias("r")).agg(F.min("doc").alias("component_id"))
    print_ = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    of_fp = looked_up(named, "root", least, "r", "fp").select(print_.alias("fingerprint"), "component_id")
    return fps.select("doc_id", print_.alias("fingerprint")).join(of_fp, "fingerprint").select("doc_id", "fingerprint", "component_id")


def op3_simhash(docs: DataFrame) -> DataFrame:
    return near_classes(docs)


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline: of each class the row with the least doc_id stays, null last, and of rows that share it one. Linked are fingerprints
    within BUDGET bits, and near copies that the wide fingerprints find. All goes by row ids, so equal or null doc_ids link nothing."""
    rows = written(docs.select(*DOCUMENT_COLUMNS, F.monotonically_increasing_id().alias("rid")), "rows")
    own = rows.select(F.col("rid").alias("doc_id"), "text")
    fps = written(fingerprints(own, count=WIDE, sketch=True), "fingerprints")
    close = written(_classes(fps.select("doc_id", "fp"), BUDGET, BLOCKS).select(F.col("doc_id").alias("doc"), F.col("component_id").alias("cls")), "close")
    nodes = written(fps.groupBy("wide", "sketch").agg(F.min("doc_id").alias("doc")).join(close, "doc"), "nodes")
    pairs = linked = roots = None
    for kind in ({"count": FIRST, "first": True}, {}):
        named = nodes if roots is None else nodes.join(roots, "cls", "left").select("doc", "wide", "sketch", F.coalesce("root", "cls").alias("cls"))
        new = wide_pairs(named, **kind)
        # what was compared and is still between classes was refuted
        new = written(new if pairs is None else new.join(pairs.select("a", "b"), ["a", "b"], "left_anti"), "pairs")
        near = _linked(new, own)
        pairs, linked = (new, near) if pairs is None else (pairs.union(new), linked.union(near))
        roots = classes_of_links(linked).select(F.col("node").alias("cls"), "root")
    place = F.struct(F.col("doc_id").isNull().alias("null"), "doc_id", "rid")
    least = rows.select("rid", "doc_id").join(close, F.col("rid") == F.col("doc")).groupBy("cls").agg(F.min(place).alias("least"))
    keep = least.join(roots, "cls", "left").groupBy(F.coalesce("root", "cls").alias("root")).agg(F.min("least").alias("least")).select(F.col("least.rid").alias("rid"))
    return rows.join(keep, "rid", "left_semi").select(*DOCUMENT_COLUMNS)


def _linked(pairs: DataFrame, docs: DataFrame) -> DataFrame:
    """(a, b): the classes of those pairs that are near copies."""
    return written(near_copies(pairs, docs).select(F.col("ca").alias("a"), F.col("cb").alias("b")), "linked")
