"""SimHash near-duplicates by pigeonring filtering.

A fingerprint has 64 bits; two of them link at ``reach`` or fewer differing
bits. The bits are cut into ``segments`` around a ring. If two fingerprints
differ in at most ``reach`` bits, then from some segment on every chain of
consecutive segments stays within its share of the budget: the first l
segments together differ in at most ``floor(l * reach / segments)`` bits. So
the first few segments of that chain are equal outright; they are the join
key. The rest of the chain is checked before the full distance.

There are as many segments as the number of fingerprints asks for: more of
them make longer keys, under which fewer fingerprints meet by chance, and more
rows. Only distinct fingerprints take part. Keys that a few fingerprints share
are compared pair by pair. A key that many share (a large family of near copies)
would give a number of pairs that grows with its square, so its members go
another, exact way: each is listed under itself and its one-bit neighbours,
and two fingerprints that meet under any of these are at most two bits apart.
At most 65 fingerprints can meet under one such hub, and each links to the
smallest. Components come out the same, and no group is ever larger than a
constant.

Components of few links (``MOST_COLLECTED``) are found on the driver, as a
shuffled round costs a task for every partition however few the rows are. More
links go through alternating star contractions, with a reliable checkpoint each
round. Both give the same roots. Then documents fetch their component by
fingerprint. A hot fingerprint only ever sits on the streamed side of that
join, where adaptive execution can split it.

Null and empty texts have the fingerprint zero and link like any other.
Repeated rows and ids stay; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from warpspan.llm.common import cut, discard, freeing, utf8, values

SEED = 42
SHINGLE = 3
REACH = 2
#: Numbers of segments to choose from; all odd, as an even number's keys are no longer than the next lower one's.
RINGS = (5, 9, 17, 33)
#: Fingerprints of one key that are still compared pair by pair.
FEW = 24

_LANES = np.uint64(0x0001000100010001)


def shingle_hashes(text: bytes | None, width: int = SHINGLE) -> list[int]:
    """XXH64 of every run of ``width`` words, ASCII letters lower-cased; of the whole sequence if shorter."""
    words = text.lower().split() if text else []
    if not words:
        return []
    hashed = xxhash.xxh64_intdigest
    if len(words) <= width:
        return [hashed(b" ".join(words), SEED)]
    return [hashed(b" ".join(run), SEED) for run in zip(*(words[k:] for k in range(width)), strict=False)]


def majority(hashes: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """One fingerprint for each run of ``sizes[i]`` hashes: bits set in over half of them.

    Bits are counted in four 16-bit lanes at once; runs are cut at 65,535
    hashes so that no lane overflows.
    """
    out = np.zeros(len(sizes), dtype=np.uint64)
    if not len(hashes):
        return out
    pieces = -(-sizes // 65_535)
    owner = np.repeat(np.arange(len(sizes)), pieces)
    rank = np.arange(len(owner)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    starts = (np.cumsum(sizes) - sizes)[owner] + rank * 65_535
    for shift in range(16):
        lanes = np.add.reduceat((hashes >> np.uint64(shift)) & _LANES, starts)
        for lane in range(4):
            part = (lanes >> np.uint64(16 * lane)) & np.uint64(0xFFFF)
            ones = np.bincount(owner, weights=part.astype(np.float64), minlength=len(sizes))
            out |= (2 * ones > sizes).astype(np.uint64) << np.uint64(shift + 16 * lane)
    return out


def fingerprint(text: str | Column = "text", width: int = SHINGLE) -> Column:
    """The text's fingerprint as a signed 64-bit number."""

    @F.arrow_udf("bigint")
    def prints(texts: pa.Array) -> pa.Array:
        out = []
        for start in range(0, len(texts), 256):
            hashes: list[int] = []
            sizes = []
            for text in values(texts.slice(start, 256)):
                own = shingle_hashes(text, width)
                hashes += own
                sizes.append(len(own))
            out.append(majority(np.array(hashes, dtype=np.uint64), np.array(sizes, dtype=np.int64)).view(np.int64))
        return pa.array(np.concatenate(out) if out else np.array([], np.int64), pa.int64())

    return prints(utf8(text))


def ring(segments: int) -> list[tuple[int, int]]:
    """Start and width of each segment, widths as equal as can be."""
    cuts = [64 * k // segments for k in range(segments + 1)]
    return [(a, b - a) for a, b in zip(cuts, cuts[1:], strict=False)]


def segments_for(prints: int) -> int:
    """The fewest segments under whose shortest key less than one other fingerprint is expected by chance."""
    for segments in RINGS:
        keys = [next(mask for mask, allowed in reversed(_chain_masks(start, segments, REACH)) if allowed == 0) for start in range(segments)]
        if prints < 1 << min((mask % (1 << 64)).bit_count() for mask in keys):
            return segments
    return RINGS[-1]


def _mask(parts: list[tuple[int, int]]) -> int:
    bits = sum(((1 << width) - 1) << start for start, width in parts)
    return bits - (1 << 64) if bits >= 1 << 63 else bits


def _lit(mask: int) -> Column:
    return F.lit(mask).cast("bigint")


def _chain_masks(start: int, segments: int, reach: int) -> list[tuple[int, int]]:
    """Of the chain from a segment: the mask of its first l segments and the bits that may differ there."""
    parts = ring(segments)
    turned = [parts[(start + k) % segments] for k in range(segments)]
    return [(_mask(turned[: length + 1]), (length + 1) * reach // segments) for length in range(segments)]


def _keys(prints: DataFrame, segments: int, reach: int) -> DataFrame:
    """``start, bits, fp``: for every start, the bits of the segments that must be equal."""
    starts = []
    for start in range(segments):
        equal = [mask for mask, allowed in _chain_masks(start, segments, reach) if allowed == 0]
        starts.append(F.struct(F.lit(start).cast("byte").alias("start"), F.col("fp").bitwiseAND(_lit(equal[-1])).alias("bits")))
    return prints.select("fp", F.inline(F.array(*starts)))


def _within(a: Column, b: Column, start: Column, segments: int, reach: int) -> Column:
    """The chain's budgets in order, then the full distance."""
    differ = a.bitwiseXOR(b)
    chain = F.lit(False)
    for first in range(segments):
        budgets = [
            F.bit_count(differ.bitwiseAND(_lit(mask))) <= allowed
            for mask, allowed in _chain_masks(first, segments, reach)
            if 0 < allowed < reach
        ]
        ok = start == first
        for budget in budgets:
            ok = ok & budget
        chain = chain | ok
    return chain & (F.bit_count(differ) <= reach)


def near_pairs(prints: DataFrame, segments: int | None = None, few: int = FEW) -> DataFrame:
    """Links ``a < b`` between distinct fingerprints that join all within two bits of each other.

    ``prints`` has one column ``fp`` without repeats. ``segments`` follow from their number if not given. Keys shared by up to
    ``few`` fingerprints give every pair in reach; keys shared by more give
    hub links with the same connected components.
    """
    reach = REACH
    segments = segments or segments_for(prints.count())
    keys = _keys(prints, segments, reach)
    shared = keys.groupBy("start", "bits").agg(F.count("*").alias("n"), F.min("fp").alias("a"), F.max("fp").alias("b"))
    sizes = cut(shared.where("n > 1"))
    two = sizes.where("n = 2").select("a", "b", "start")
    some = (
        keys.join(sizes.where(f"n > 2 and n <= {few}").select("start", "bits"), ["start", "bits"])
        .groupBy("start", "bits")
        .agg(F.sort_array(F.collect_list("fp")).alias("fps"))
        .select("start", F.explode("fps").alias("a"), "fps")
        .select("start", "a", F.explode(F.filter("fps", lambda x: x > F.col("a"))).alias("b"))
    )
    paired = two.unionByName(some).where(_within(F.col("a"), F.col("b"), F.col("start"), segments, reach)).select("a", "b")
    crowded = keys.join(sizes.where(f"n > {few}").select("start", "bits"), ["start", "bits"]).select("fp").distinct()
    flips = F.array(F.col("fp"), *(F.col("fp").bitwiseXOR(_lit(_mask([(bit, 1)]))) for bit in range(64)))
    hubs = (
        crowded.select("fp", F.explode(flips).alias("hub"))
        .groupBy("hub")
        .agg(F.sort_array(F.collect_list("fp")).alias("fps"))
        .where(F.size("fps") > 1)
        .select(F.element_at("fps", 1).alias("a"), F.explode(F.slice("fps", 2, 64)).alias("b"))
    )
    return paired.unionByName(hubs).distinct()


#: Links whose components the driver finds (16 bytes each); more are contracted by the executors.
MOST_COLLECTED = 500_000


def smallest_reachable(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of links and the smallest node of each one's component."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    u, v = at[: len(u)], at[len(u) :]
    root = np.arange(len(nodes))
    while len(u):
        one, two = root[u], root[v]
        np.minimum.at(root, np.maximum(one, two), np.minimum(one, two))
        while not np.array_equal(root, up := root[root]):
            root = up
        apart = root[u] != root[v]
        u, v = u[apart], v[apart]
    return nodes, nodes[root]


def components(links: DataFrame, most_rounds: int = 60, most_collected: int = MOST_COLLECTED) -> DataFrame:
    """``node, root`` for every node of ``links(a, b)`` but the roots; root is the smallest node of its component."""
    edges = cut(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v"))
    if edges.count() > most_collected:
        return _contracted(edges, most_rounds)
    table = edges.toArrow()
    discard(edges)
    node, root = smallest_reachable(*(np.array(table.column(c), dtype=np.int64) for c in ("u", "v")))
    moved = node != root
    return F.broadcast(links.sparkSession.createDataFrame(pa.table({"node": node[moved], "root": root[moved]})))


def _contracted(links: DataFrame, most_rounds: int) -> DataFrame:
    """``components`` of links ``u > v`` that ``cut`` wrote.

    Each round is a large-star step (a node's larger neighbours move to its
    smallest one) and a small-star step (its smaller neighbours move to the
    smallest); rounds grow with the logarithm of the longest chain. Stars keep
    one row per link, so no neighbourhood is ever collected.
    """
    edges = cut(links.distinct())
    discard(links)
    before = None
    for _ in range(most_rounds):
        both = edges.select("u", "v").union(edges.select("v", "u"))
        low = both.groupBy("u").agg(F.min("v").alias("least")).select("u", F.least("u", "least").alias("low"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("low").alias("v"))
        lowest = large.groupBy("u").agg(F.min("v").alias("low"))
        small = large.join(lowest, "u").select(F.greatest("v", "low").alias("u"), "low").union(lowest.select("u", "low"))
        last, edges = edges, cut(small.where("u <> low").select("u", F.col("low").alias("v")).distinct())
        discard(last)
        with freeing(edges.sparkSession):
            state = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == before:
            out = edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
            out._cut_at = edges._cut_at
            return out
        before = state
    raise RuntimeError("components did not settle")


def text_mark(text: str | Column = "text") -> Column:
    """A digest that tells the texts under one id apart."""
    return F.xxhash64(F.col(text) if isinstance(text, str) else text)


def classify(documents: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, mark, fp, root, component_id`` of every document; the component's id is its smallest document id.

    Documents without an id count for links but not for the smallest id.
    """
    printed = cut(documents.select(F.col(id_column).alias("doc_id"), text_mark(text).alias("mark"), fingerprint(text).alias("fp")))
    return grouped(printed, near_pairs(cut(printed.select("fp").distinct())))


def grouped(printed: DataFrame, links: DataFrame) -> DataFrame:
    """Adds ``root`` (the component's smallest node) and ``component_id`` to rows with ``doc_id, fp``, by the links between nodes."""
    firsts = cut(printed.groupBy("fp").agg(F.min("doc_id").alias("first_id")))
    found = components(links)
    members = found.union(found.select("root", "root").distinct()).toDF("fp", "root")
    smallest = members.join(firsts, "fp").groupBy("root").agg(F.min("first_id").alias("component_id"))
    moved = members.join(smallest, "root").select("fp", "root", "component_id")
    of_print = cut(
        firsts.join(moved, "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), F.coalesce("component_id", "first_id").alias("component_id"))
    )
    discard(firsts)
    discard(found)
    return printed.join(of_print, "fp").select(*printed.columns, "root", "component_id")


def hex_print(fp: str = "fp") -> Column:
    """The fingerprint as 16 lower-case hexadecimal digits."""
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


#: Ids that are sent to every executor (8 bytes each); more go by a shuffled join.
MOST_SENT = 2_000_000


def keep_one(documents: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents with one of each component; ``keep_first`` says which."""
    return keep_first(documents, classify(documents, id_column, text), id_column, text)


def keep_first(documents: DataFrame, classes: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """One document of each component: the one of the smallest id, of that id's texts the one with the smallest mark.

    ``classes`` has a row ``doc_id, mark, root`` for each document. A row
    without an id stays only if its whole component has none. Of rows alike in
    id and text the one whose columns come first as JSON stays. Texts move only
    if more rows go than ``MOST_SENT``.
    """
    rank = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "mark")
    best = classes.groupBy("root").agg(F.min(rank).alias("best"), F.count("*").alias("size")).where("size > 1")
    judged = classes.join(best, "root").select("doc_id", "mark", (rank != F.col("best")).alias("loses"))
    named = cut(
        judged.groupBy(F.col("doc_id").alias("_near_id"), F.col("mark").alias("_near_mark"))
        .agg(F.first("loses").alias("_near_loses"), F.count("*").alias("_near_rows"))
        .where("_near_loses or _near_rows > 1")
    )
    again = named.where("not _near_loses")
    if named.count() <= MOST_SENT:
        named, again = F.broadcast(named), F.broadcast(again)
    match = lambda ids: documents[id_column].eqNullSafe(ids["_near_id"]) & (text_mark(documents[text]) == ids["_near_mark"])
    single = documents.join(named, match(named), "left_anti")
    row = F.struct(*(F.col(f"`{name}`") for name in documents.columns))
    repeated = documents.join(again, match(again), "left_semi").select(F.col(id_column).alias("_id"), text_mark(text).alias("_mark"), row.alias("_row"))
    one = repeated.groupBy("_id", "_mark").agg(F.min_by("_row", F.to_json("_row")).alias("_row"))
    return single.unionByName(one.select("_row.*"))
