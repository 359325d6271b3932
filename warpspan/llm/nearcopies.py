"""Near copies: groups of documents whose five-word shingle sets are alike to 0.8 by Jaccard.

This is the near-duplicate operator's setting for a similarity of whole sets.
Its method comes first: fingerprints of the five-word runs, pairs of them in
reach by pigeonring chains, an exact check of each pair, and star contractions.
Fingerprints of 64 bits can't decide the rest: at a similarity of 0.8 two of
them differ in ten bits, give or take three, and no key is left that such a
pair must share. So what the fingerprints leave apart is compared by candidates
from the sets themselves.

Two sets that are alike to 0.8 share an element among the first fifth (and
one) of each, whatever order the elements are put in, as long as it is one
order for all. These prefixes are the join keys, so no pair is missed. Common
shingles come last in the order, or else every text with a common line would
meet at it; how common they are is estimated from some of the documents, which
changes the cost and never the result.

A candidate pair is checked by size, then by a parity map: a set's elements
are dealt to 256 places, each of which holds whether their number is odd. Two
maps differ in no more places than the sets in elements, and alike sets differ
in a ninth of their elements at most. Both tests are part of the join on keys,
so pairs that fail are never rows. Only for pairs that pass are the whole sets
fetched and their Jaccard similarity computed.

Equal sets are one node. Keys that a few nodes share give every pair across
components. At a key that many share (a large family) all members are compared
with one of them, those alike become one component, and only pairs across
components are left; after some rounds what is left is compared in full. Members
of one key that are in different components after that cost a comparison of two
maps for each pair, and pairs that the maps leave are rows, so a large crowd of
texts that are almost alike still takes time and rows by its square there.

Null and empty texts have the empty set and count as equal. Repeated rows and
ids stay; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from warpspan.llm import simhash
from warpspan.llm.common import cut, discard, freeing, utf8, values

WIDTH = 5
#: The least similarity as a fraction.
PART, WHOLE = 4, 5
#: Nodes of one key that are still compared pair by pair at once.
FEW = 24
#: Rounds against one member of each crowded key before the rest is compared in full.
ROUNDS = 4
#: One document in so many is counted for the order of shingles.
COUNTED = 16
#: Shingles that are put last, at most (8 bytes each to every task), and the count among the counted that makes one common.
MOST_COMMON, OFTEN = 500_000, 3
_MAPS = ("p0", "p1", "p2", "p3")


def shingle_set(text: bytes | None) -> np.ndarray:
    """Sorted distinct hashes of a text's five-word runs."""
    return np.unique(np.array(simhash.shingle_hashes(text, WIDTH), dtype=np.uint64))


def prefix_size(n: int) -> int:
    """Elements of a set of n that must hold one of any set alike to it."""
    return n - -(-PART * n // WHOLE) + 1 if n else 0


def packed(hashes: np.ndarray) -> bytes:
    """A set as the upper 40 bits of its hashes, five bytes each; among them two shingles of a pair are alike by chance once in a million pairs."""
    upper = np.unique(hashes >> np.uint64(24)).astype("<u8")
    return upper.view(np.uint8).reshape(-1, 8)[:, :5].tobytes()


def unpacked(body: bytes) -> np.ndarray:
    wide = np.zeros((len(body) // 5, 8), dtype=np.uint8)
    wide[:, :5] = np.frombuffer(body, np.uint8).reshape(-1, 5)
    return wide.view("<u8").ravel()


def _node(hashes: np.ndarray) -> int:
    value = xxhash.xxh3_64_intdigest(hashes.tobytes())
    return value - (1 << 64) if value >= 1 << 63 else value


def common_shingles(documents: DataFrame, text: str = "text") -> np.ndarray:
    """Common shingles, rarest first, as far as some of the documents tell."""

    def make(source):
        for batch in source:
            sets = [shingle_set(t) for t in values(batch.column(0))]
            seen, counts = np.unique(np.concatenate(sets) if sets else np.array([], np.uint64), return_counts=True)
            yield pa.record_batch([pa.array(seen.view(np.int64)), pa.array(counts, pa.int64())], names=["key", "n"])

    some = documents.select(utf8(text).alias("text")).where(F.pmod(F.xxhash64("text"), F.lit(COUNTED)) == 0).dropDuplicates()
    counted = some.mapInArrow(make, "key bigint, n bigint").groupBy("key").agg(F.sum("n").alias("n")).where(F.col("n") >= OFTEN)
    table = counted.orderBy(F.desc("n"), "key").limit(MOST_COMMON).select("key").toArrow()
    return np.array(table.column("key"), dtype=np.int64).view(np.uint64)[::-1].copy()


def parity_map(hashes: np.ndarray) -> np.ndarray:
    """256 parities in four 64-bit numbers."""
    odd = (np.bincount((hashes >> np.uint64(20)).astype(np.uint8), minlength=256) & 1).astype(np.uint8)
    return np.packbits(odd).view(np.int64)


def signed(documents: DataFrame, common: np.ndarray, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, mark, fp, fingerprint, n, p0 .. p3, keys``: each document's node, its fingerprint, the size of its set, its parity map and its prefix."""
    by_value = np.argsort(common)
    known = common[by_value]

    def make(source):
        for batch in source:
            nodes, sizes, keys, maps = [], [], [], np.zeros((batch.num_rows, 4), dtype=np.int64)
            prints, runs = [], []
            for row, value in enumerate(values(batch.column(2))):
                runs.append(np.array(simhash.shingle_hashes(value, WIDTH), dtype=np.uint64))
                if len(runs) == 256 or row == batch.num_rows - 1:
                    prints.append(simhash.majority(np.concatenate(runs), np.array([len(r) for r in runs], dtype=np.int64)))
                    last, runs = runs[-1], []
                else:
                    last = runs[-1]
                hashes = np.unique(last)
                at = np.minimum(np.searchsorted(known, hashes), max(len(known) - 1, 0))
                late = known[at] == hashes if len(known) else np.zeros(len(hashes), bool)
                ordered = np.concatenate([hashes[~late], common[np.sort(by_value[at[late]])]])
                nodes.append(_node(hashes))
                sizes.append(len(hashes))
                maps[row] = parity_map(hashes)
                keys.append(ordered[: prefix_size(len(hashes))].view(np.int64))
            ends = np.cumsum([0, *map(len, keys)])
            flat = np.concatenate(keys) if keys else np.array([], np.int64)
            lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat))
            printed = pa.array(np.concatenate(prints).view(np.int64) if prints else np.array([], np.int64))
            columns = [batch.column(0), batch.column(1), pa.array(nodes, pa.int64()), printed, pa.array(sizes, pa.int32()), *(pa.array(maps[:, k]) for k in range(4)), lists]
            yield pa.record_batch(columns, names=["doc_id", "mark", "fp", "fingerprint", "n", *_MAPS, "keys"])

    kind = documents.schema[id_column].dataType.simpleString()
    source = documents.select(F.col(id_column).alias("doc_id"), simhash.text_mark(text).alias("mark"), utf8(text).alias("text"))
    return source.mapInArrow(make, f"doc_id {kind}, mark bigint, fp bigint, fingerprint bigint, n int, {', '.join(f'{m} bigint' for m in _MAPS)}, keys array<bigint>")


class Verifier:
    """Tells which candidate pairs are alike; fetches sets only for those that size and parity map leave."""

    def __init__(self, documents: DataFrame, nodes: DataFrame, id_column: str, text: str):
        self.documents, self.id_column, self.text = documents, id_column, text
        first = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "mark")).alias("first")
        self.known = cut(nodes.groupBy("fp").agg(F.first("n").alias("n"), *(F.first(m).alias(m) for m in _MAPS), first))

    def done(self) -> None:
        discard(self.known)

    def _sets(self, wanted: DataFrame) -> DataFrame:
        """``fp, hashes``: the whole sets of the wanted nodes, from one document of each."""
        chosen = self.known.join(wanted, "fp", "left_semi").select(F.col("first.doc_id").alias("_set_id"), F.col("first.mark").alias("_set_mark"))
        if wanted.count() <= simhash.MOST_SENT:
            chosen = F.broadcast(chosen)
        mine = self.documents[self.id_column].eqNullSafe(chosen["_set_id"]) & (simhash.text_mark(self.documents[self.text]) == chosen["_set_mark"])

        def make(source):
            for batch in source:
                for start in range(0, batch.num_rows, 256):
                    sets = [shingle_set(t) for t in batch.column(0).slice(start, 256).to_pylist()]
                    yield pa.record_batch([pa.array([_node(s) for s in sets], pa.int64()), pa.array([packed(s) for s in sets], pa.binary())], names=["fp", "hashes"])

        texts = self.documents.join(chosen, mine, "left_semi").select(utf8(self.text).alias("text"))
        return cut(texts.mapInArrow(make, "fp bigint, hashes binary"))

    def mapped(self) -> DataFrame:
        """``fp, n, p0 .. p3`` of every node."""
        return self.known.select("fp", "n", *_MAPS)

    def alike(self, pairs: DataFrame, tested: bool = False) -> DataFrame:
        """The pairs ``a, b`` whose sets are alike; ``tested`` says that size and parity maps left them."""
        side = lambda name: self.mapped().toDF(name, f"n_{name}", *(f"{m}_{name}" for m in _MAPS))
        left = cut(pairs if tested else pairs.join(side("a"), "a").join(side("b"), "b").where(_may_be_alike()).select("a", "b"))
        wanted = cut(left.select(F.explode(F.array("a", "b")).alias("fp")).distinct())
        sets = self._sets(wanted)
        # Few pairs go to the sets, so that a set moves once, to its partner.
        sent = F.broadcast(left) if left.count() <= simhash.MOST_SENT else left

        def verify(source):
            for batch in source:
                good = []
                for start in range(0, batch.num_rows, 256):
                    piece = batch.slice(start, 256)
                    for x, y in zip(piece.column(2).to_pylist(), piece.column(3).to_pylist(), strict=True):
                        x, y = unpacked(x), unpacked(y)
                        both = len(np.intersect1d(x, y, assume_unique=True))
                        good.append(WHOLE * both >= PART * (len(x) + len(y) - both))
                yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

        first, second = sets.toDF("a", "_a"), sets.toDF("b", "_b")
        met = first.join(sent, "a").join(second, "b").select("a", "b", "_a", "_b")
        found = cut(met.mapInArrow(verify, "a bigint, b bigint").distinct())
        for table in (left, wanted, sets):
            discard(table)
        return found


def _near_size(a: Column, b: Column) -> Column:
    return WHOLE * F.least(a, b) >= PART * F.greatest(a, b)


def _may_be_alike() -> Column:
    """Size and parity map, of rows with ``n_a, p0_a .. p3_b``."""
    differ = sum((F.bit_count(F.col(f"{m}_a").bitwiseXOR(F.col(f"{m}_b"))) for m in _MAPS), F.lit(0))
    return _near_size(F.col("n_a"), F.col("n_b")) & ((WHOLE + PART) * differ <= (WHOLE - PART) * (F.col("n_a") + F.col("n_b")))


def _every_pair(members: DataFrame) -> DataFrame:
    """Pairs of different components at a key that size and parity map leave; ``members`` has ``key, fp, root, n, p0 .. p3``."""
    side = lambda name: members.select("key", *(F.col(c).alias(f"{c}_{name}") for c in ("fp", "root", "n", *_MAPS)))
    near = (F.col("fp_a") < F.col("fp_b")) & (F.col("root_a") != F.col("root_b")) & _may_be_alike()
    one, two = side("a"), side("b")
    return one.join(two, (one["key"] == two["key"]) & near).select(F.col("fp_a").alias("a"), F.col("fp_b").alias("b")).distinct()


def _rooted(members: DataFrame, links: DataFrame) -> DataFrame:
    """Members with their components, written."""
    found = simhash.components(links)
    out = cut(members.drop("root").join(found.toDF("fp", "root"), "fp", "left").withColumn("root", F.coalesce("root", "fp")))
    discard(found)
    return out


def fingerprint_pairs(nodes: DataFrame) -> DataFrame:
    """Candidates ``a, b`` by the operator's method: nodes of one fingerprint, and of two within its reach, by the first node of each."""
    every = cut(nodes.select("fp", "fingerprint").distinct())
    firsts = cut(every.groupBy("fingerprint").agg(F.min("fp").alias("first")))
    same = every.join(firsts, "fingerprint").where("fp <> first").select(F.col("first").alias("a"), F.col("fp").alias("b"))
    near = simhash.near_pairs(firsts.select(F.col("fingerprint").alias("fp"))).toDF("one", "two")
    across = near.join(firsts.toDF("one", "x"), "one").join(firsts.toDF("two", "y"), "two")
    return same.unionByName(across.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))).distinct()


def near_links(documents: DataFrame, nodes: DataFrame, id_column: str = "doc_id", text: str = "text", few: int = FEW) -> DataFrame:
    """Links ``a, b`` between alike nodes that have the components of all such pairs."""
    check = Verifier(documents, nodes, id_column, text)
    try:
        return _all_links(check, nodes, few)
    finally:
        check.done()


def _all_links(check: Verifier, nodes: DataFrame, few: int) -> DataFrame:
    links = check.alike(fingerprint_pairs(nodes))
    postings = nodes.select("fp", F.explode("keys").alias("key"))
    shared = postings.groupBy("key").agg(F.min("fp").alias("a"), F.max("fp").alias("b")).where("a <> b").select("key")
    shared = cut(shared)
    met = cut(postings.join(shared, "key", "left_semi").distinct())
    discard(shared)
    # Of keys with the same members one is enough.
    marks = [F.sum(F.xxhash64("fp", F.lit(k)).cast("decimal(38,0)")).alias(f"mark{k}") for k in (0, 1)]
    lists = met.groupBy("key").agg(F.count("*").alias("size"), *marks)
    single = cut(lists.groupBy("size", "mark0", "mark1").agg(F.min("key").alias("key")).select("key", "size"))
    members = _rooted(met.join(single, "key").join(check.mapped(), "fp"), links)
    discard(met)
    discard(single)
    links = links.unionByName(check.alike(_every_pair(members.where(F.col("size") <= few)), tested=True))
    crowded = cut(members.where(F.col("size") > few))
    discard(members)
    if crowded.isEmpty():
        discard(crowded)
        return links
    for turn in range(ROUNDS + 1):
        last, crowded = crowded, _rooted(crowded, links)
        discard(last)
        parts = crowded.groupBy("key", "root").agg(F.count("*").cast("double").alias("c"))
        sizes = cut(parts.groupBy("key").agg(F.sum("c").alias("m"), ((F.sum("c") ** 2 - F.sum(F.col("c") ** 2)) / 2).alias("open")).where("open > 0"))
        state = sizes.agg(F.sum("m").alias("rows"), F.sum("open").alias("open")).first()
        if not state.open:
            break
        open_keys = crowded.join(sizes.select("key"), "key", "left_semi")
        if turn == ROUNDS or state.open <= few * state.rows:
            links = links.unionByName(check.alike(_every_pair(open_keys), tested=True))
            break
        heads = open_keys.groupBy("key").agg(F.min_by(F.struct("fp", "root"), F.xxhash64("fp", F.lit(turn))).alias("head"))
        rest = open_keys.join(heads, "key").where(F.col("head.root") != F.col("root"))
        pairs = rest.select(F.least("fp", "head.fp").alias("a"), F.greatest("fp", "head.fp").alias("b")).distinct()
        links = links.unionByName(check.alike(pairs))
        discard(sizes)
    discard(sizes)
    discard(crowded)
    return links


def classify(documents: DataFrame, id_column: str = "doc_id", text: str = "text", few: int = FEW) -> DataFrame:
    """``doc_id, mark, fp, root, component_id`` of every document; the component's id is its smallest document id."""
    with freeing(documents.sparkSession):
        nodes = cut(signed(documents, common_shingles(documents, text), id_column, text))
        links = near_links(documents, nodes, id_column, text, few)
        printed = cut(nodes.select("doc_id", "mark", "fp"))
        discard(nodes)
    return simhash.grouped(printed, links)


def keep_one(documents: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents with one of each group of near copies, as ``simhash.keep_first`` chooses it."""
    return simhash.keep_first(documents, classify(documents, id_column, text), id_column, text)
