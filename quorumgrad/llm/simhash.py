"""Near-duplicates by SimHash, found through a byte-position inverted index with count filtering.

A 64-bit fingerprint is eight bytes at eight positions.  Two fingerprints that differ in at most 3 bits share at least
5 positional bytes, so a posting list keyed by positional bytes finds every such pair.  Lists of one byte would hold
1/256 of all fingerprints each and their pairs would grow with the square of the corpus; lists here are keyed by four
positional bytes at once.  ``position_sets`` is a family of position quadruples of which every 5 shared positions
contain at least one, so no pair is lost.  Each candidate pair's shared positional bytes are tallied, pairs with fewer
than the guaranteed 5 go, and the rest is verified bit by bit.  Equal fingerprints are one node of the graph, so a
group of exact copies makes no pairs.

Defined results: a null, empty or blank text has fingerprint zero and links like any other; rows with a null doc_id keep
their row, take part in links and give the smallest id only if no row of the component has one (then null); repeated rows
give one result row each; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import as_row, batch_texts, materialized, only

SEED, BYTES = 42, 8


def fingerprint(text: bytes, shingle: int = 3) -> int:
    """SimHash of lower-cased (A-Z) word shingles, repeats included."""
    words = text.lower().split()  # bytes: ASCII letters and ASCII white space only
    if not words:
        return 0
    line = b" ".join(words)
    if len(words) <= shingle:
        return _majority(np.array([xxhash.xxh64_intdigest(line, SEED)], np.uint64))
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = (np.concatenate([[0], ends[:-1]]))[: len(words) - shingle + 1].tolist()
    digest = xxhash.xxh64_intdigest
    hashes = [digest(line[a:b], SEED) for a, b in zip(starts, (ends[shingle - 1 :] - 1).tolist(), strict=True)]
    return _majority(np.array(hashes, np.uint64))


def _majority(hashes: np.ndarray, block: int = 1 << 16) -> int:
    """Bits set in over half of the hashes; in blocks, so that memory doesn't follow the text's length."""
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), block):
        part = hashes[at : at + block].astype(">u8").view(np.uint8).reshape(-1, BYTES)
        ones += np.unpackbits(part, axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes)).view(">u8")[0])


@cache
def position_sets(positions: int = BYTES, shared: int = 5, width: int = 4) -> tuple[tuple[int, ...], ...]:
    """A small family of ``width``-subsets such that any ``shared`` positions contain one (greedy cover)."""
    open_sets = {frozenset(x) for x in combinations(range(positions), shared)}
    chosen = []
    while open_sets:
        best = max(combinations(range(positions), width), key=lambda s: sum(set(s) <= x for x in open_sets))
        chosen.append(best)
        open_sets = {x for x in open_sets if not set(best) <= x}
    return tuple(chosen)


def identified(docs: DataFrame) -> DataFrame:
    """(doc_id, of, text): rows are told apart by their id and their text's hash ``of``."""
    own = only(docs, "doc_id", "text")
    return own.select(own["doc_id"].cast("long").alias("doc_id"), F.xxhash64("text").alias("of"), "text")


def with_fingerprint(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """(doc_id, of, fp) of each row; ``fp`` holds the 64 bits as a signed long.  Narrow."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, starts, ends = batch_texts(batch.column(2))
            found = np.array([fingerprint(raw[a:b].tobytes(), shingle) for a, b in zip(starts, ends, strict=True)], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(found.view(np.int64))], names=["doc_id", "of", "fp"])

    return identified(docs).mapInArrow(run, "doc_id long, of long, fp long")


def byte_at(fp: Column, position: int) -> Column:
    return F.shiftright(fp, 8 * position).bitwiseAND(F.lit(255))


def links(prints: DataFrame, max_bits: int = 3) -> DataFrame:
    """Pairs (a, b), a < b, of different fingerprints that differ in at most ``max_bits`` bits.

    ``prints`` has one row per fingerprint (fp).  A pair that meets in several posting lists is emitted by the first
    quadruple it shares only, so no distinct is needed.
    """
    need = BYTES - max_bits
    sets = position_sets(BYTES, need, need - 1)

    def key(s: tuple[int, ...]) -> Column:
        mask = sum(255 << 8 * p for p in s)
        return F.col("fp").bitwiseAND(F.lit(mask - (1 << 64) if mask >> 63 else mask))

    postings = prints.select("fp", F.posexplode(F.array(*map(key, sets))).alias("list", "bytes"))
    a, b = postings.select(F.col("fp").alias("a"), "list", "bytes"), postings.select(F.col("fp").alias("b"), "list", "bytes")
    x = F.col("a").bitwiseXOR(F.col("b"))
    tally = sum((byte_at(x, p) == 0).cast("int") for p in range(BYTES))
    first_list = F.coalesce(*[F.when(x.bitwiseAND(F.lit(sum(255 << 8 * p for p in s) - ((1 << 64) if 7 in s else 0))) == 0, F.lit(i)) for i, s in enumerate(sets)])
    pairs = a.join(b, ["list", "bytes"]).where((F.col("a") < F.col("b")) & (tally >= need) & (F.bit_count(x) <= max_bits) & (first_list == F.col("list")))
    return pairs.select("a", "b")


def components(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """(node, root): the smallest node reachable, for every node that has an edge.

    Alternates hooking larger neighbours onto the smallest one and shortening paths, until the edge set is stable.
    Every round is written to the shared folder, so no lineage grows and nothing is collected.
    """
    both = lambda e: e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
    edges = materialized(spark, edges, "edges", few=True)
    total = -1
    while True:
        # Large star: neighbours above a node hook onto the smallest of its neighbourhood.
        near = both(edges)
        low = near.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = near.join(low, "a").where(F.col("b") > F.col("a")).select(F.col("m").alias("a"), "b").where(F.col("a") < F.col("b")).distinct()
        # Small star: a node and its lower neighbours hook onto the smallest of them.
        down = large.select(F.col("b").alias("n"), F.col("a").alias("m"))
        least = down.groupBy("n").agg(F.min("m").alias("r"))
        small = down.join(least, "n")
        step = small.select(F.col("r").alias("a"), F.col("m").alias("b")).union(least.select(F.col("r").alias("a"), F.col("n").alias("b")))
        edges_next = materialized(spark, step.where(F.col("a") < F.col("b")).distinct(), "edges", few=True)
        state = edges_next.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        edges = edges_next
        if state == total:
            return edges.select(F.col("b").alias("node"), F.col("a").alias("root"))
        total = state


def classes_of(spark: SparkSession, rows: DataFrame, max_bits: int = 3) -> DataFrame:
    """(fp, root, component_id) of each fingerprint of ``rows`` (doc_id, fp)."""
    prints = materialized(spark, rows.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "prints", few=True)
    joined = components(spark, links(prints.select("fp"), max_bits))
    linked = prints.join(joined.select(F.col("node").alias("fp"), "root"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    named = linked.groupBy("root").agg(F.min("first_id").alias("component_id"))
    return linked.join(named, "root").select("fp", "root", "component_id")


def near_duplicates(spark: SparkSession, docs: DataFrame, shingle: int = 3, max_bits: int = 3) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id of each row of ``docs``."""
    rows = materialized(spark, with_fingerprint(docs, shingle), "fingerprints")
    hex16 = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return rows.join(classes_of(spark, rows, max_bits), "fp").select("doc_id", hex16.alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame, rows: DataFrame, classes: DataFrame, key: str) -> DataFrame:
    """One row of each component, columns as in ``docs``: the one of the smallest doc_id (null last), of equal ids that
    of the smallest text hash, and of rows equal in both any one.

    ``rows`` has (doc_id, of, key), ``classes`` (key, root).  Rows of a component are reduced before they are shuffled.
    """
    first = F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "of")).alias("first")
    best = rows.groupBy(key).agg(first).join(classes.select(key, "root"), key).groupBy("root").agg(F.min("first").alias("first"))
    best = best.select(F.col("first.doc_id").alias("best_id"), F.col("first.of").alias("best_of"))
    keyed = docs.select(docs["doc_id"].cast("long").alias("id"), F.xxhash64(docs["text"]).alias("of"), as_row(docs))
    kept = keyed.join(best, F.col("id").eqNullSafe(F.col("best_id")) & (F.col("of") == F.col("best_of")), "left_semi")
    return kept.dropDuplicates(["id", "of"]).select("row.*")


def deduplicated(spark: SparkSession, docs: DataFrame, shingle: int = 3, max_bits: int = 3) -> DataFrame:
    """One row of each component of the 64-bit fingerprints' links, columns as in ``docs``."""
    rows = materialized(spark, with_fingerprint(docs, shingle), "fingerprints")
    return one_of_each(docs, rows, classes_of(spark, rows, max_bits), "fp")


# ---- copies with words changed, cut, appended or replaced --------------------------------------------------------
#
# Texts are sets of five-word shingles, and two are copies at a similarity (shared over all distinct shingles) of 4/5.
# Fingerprints and byte-position lists go first: texts of one fingerprint, and of fingerprints that link, are compared
# by their words, and those that are copies are joined to components.  Copies may differ in more bits than link, so
# what is left between components is found by exact filters.  Shingles have one order for all texts; of n
# shingles the first n - ceil(4n/5) + 1 are a text's head, and two copies have a shingle of both heads in common.  More
# than that, the head that ends first is shared but for what the rest of its text can make up for, so shared shingles
# are counted and nearly every pair that is left is a copy.  Each of those is compared by its words.  The order,
# whatever it is, changes only the work.
#
# Long lists (a group of thousands of versions, most of them close and not copies) have a filter more.  A text's parity
# sketch has a bit per bucket of shingles, set where their number is odd; each shingle that only one of two texts has
# flips one bit, so sketches that differ in more bits than copies can have shingles apart are no copies.  And they are
# thinned: members that stand close in some random order are tried first, what is found is joined to components, and
# then a list's members meet only those outside of its largest component.

SHINGLE = 5
#: Lists over LONG members are thinned first, each member tried with the AHEAD before it and compared by words with the
#: BEST of all its lists; they are joined in parts of BLOCK members.  None of these changes what is found in the end.
LONG, AHEAD, BEST, BLOCK = 64, 8, 4, 1024
#: 64-bit words of a parity sketch: of texts up to 1,024 shingles, 2,048 shingles, and beyond.
WORDS = (16, 32, 64)


def parity(hashes: np.ndarray) -> np.ndarray:
    """The parity sketch of a set of shingles, as signed 64-bit words."""
    bits = 64 * WORDS[min(max(len(hashes) - 1, 0) // 1024, 2)]
    odd = np.bincount(hashes & (bits - 1), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view("<i8")


def _apart(x: Column, y: Column) -> Column:
    """Bits in which two parity sketches differ; a longer one is folded, which keeps it a parity sketch."""
    words = F.least(F.size(x), F.size(y))

    def folded(s: Column) -> Column:
        halves = lambda n: F.zip_with(F.slice(s, 1, n), F.slice(s, n + 1, n), lambda p, q: p.bitwiseXOR(q))
        quarter = lambda n: F.zip_with(F.slice(halves(2 * n), 1, n), F.slice(halves(2 * n), n + 1, n), lambda p, q: p.bitwiseXOR(q))
        return F.when(F.size(s) == words, s).when(F.size(s) == 2 * words, halves(words)).otherwise(quarter(words))

    differing = F.zip_with(folded(x), folded(y), lambda p, q: F.bit_count(p.bitwiseXOR(q)).cast("int"))
    return F.aggregate(differing, F.lit(0), lambda total, n: total + n)


def _close(a: str, b: str) -> Column:
    """Whether the sizes and the sketches of two members allow them to be copies: of copies, at most a ninth of both
    sizes together is in one text only."""
    sizes = F.expr(f"5 * {a}.n >= 4 * {b}.n and 5 * {b}.n >= 4 * {a}.n")
    return F.when(sizes, 9 * _apart(F.col(f"{a}.bits"), F.col(f"{b}.bits")) <= F.col(f"{a}.n") + F.col(f"{b}.n")).otherwise(False)


def shingles_of(text: bytes) -> list[bytes]:
    """All runs of five words (of a shorter text the one it has), repeats included."""
    words = text.lower().split()
    line, n = b" ".join(words), max(1, len(words) - SHINGLE + 1)
    if n == 1:
        return [line]
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])[:n].tolist()
    return [line[a:b] for a, b in zip(starts, ends[SHINGLE - 1 :].tolist(), strict=True)]


def shingle_set(text: bytes) -> np.ndarray:
    """Distinct 62-bit hashes of a text's shingles, sorted."""
    digest = xxhash.xxh3_64_intdigest
    found = shingles_of(text)
    return np.unique(np.fromiter((digest(s, SEED) >> 2 for s in found), np.int64, len(found)))


def node_of(hashes: np.ndarray) -> int:
    """One signed 64-bit name for each set of shingles."""
    return int(np.array([xxhash.xxh3_64_intdigest(hashes.tobytes(), SEED)], np.uint64).view(np.int64)[0])


def parts(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """The batches in smaller ones, so that a worker holds few texts' shingles and results at once."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def common_shingles(docs: DataFrame, sample: int = 20_000, least: int = 3, most: int = 100_000) -> np.ndarray:
    """Shingles that several of some 20,000 texts have, rarest first.

    They come last in the order, so that boilerplate is in few heads and lists stay short.  Which ones are found (the
    sample's size, the limits) changes the order, and by that the work, but no pair.
    """
    part = max(1, docs.count() // sample)
    some = only(docs, "text").where(F.col("text").isNotNull() & (F.pmod(F.xxhash64("text"), F.lit(part)) == 0)).dropDuplicates(["text"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in parts(batches):
            raw, starts, ends = batch_texts(batch.column(0))
            for a, b in zip(starts, ends, strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(shingle_set(raw[a:b].tobytes()))], names=["shingle"])

    counts = some.mapInArrow(run, "shingle long").groupBy("shingle").agg(F.count("*").alias("k")).where(F.col("k") >= least)
    found = counts.orderBy(F.col("k").desc(), "shingle").limit(most).select("shingle").toArrow().column(0).to_numpy()
    return np.ascontiguousarray(found[::-1])


def ordered(hashes: np.ndarray, common: np.ndarray, places: np.ndarray) -> np.ndarray:
    """A set of shingles by the order of all texts: by hash, then the common ones (sorted) by their places."""
    if not len(common):
        return hashes
    at = np.minimum(np.searchsorted(common, hashes), len(common) - 1)
    return np.sort(np.where(common[at] == hashes, (1 << 62) + places[at], hashes))


def with_heads(docs: DataFrame, common: np.ndarray) -> DataFrame:
    """(doc_id, of, fp, node, n, head, bits) of each row: its fingerprint, its set's name, size, first shingles and parity
    sketch.  Narrow."""
    places = np.argsort(common, kind="stable")
    common = common[places]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in parts(batches):
            raw, starts, ends = batch_texts(batch.column(2))
            prints, nodes, sizes, heads, sketches = [], [], [], [], []
            for a, b in zip(starts, ends, strict=True):
                text = raw[a:b].tobytes()
                hashes = shingle_set(text)
                prints.append(fingerprint(text))
                nodes.append(node_of(hashes))
                sizes.append(len(hashes))
                sketches.append(parity(hashes))
                heads.append(ordered(hashes, common, places)[: len(hashes) - -(-4 * len(hashes) // 5) + 1].copy())
            fps = pa.array(np.array(prints, np.uint64).view(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), fps, pa.array(nodes, pa.int64()), pa.array(sizes, pa.int64()), _lists(heads), _lists(sketches)], names=["doc_id", "of", "fp", "node", "n", "head", "bits"])

    return identified(docs).mapInArrow(run, "doc_id long, of long, fp long, node long, n long, head array<long>, bits array<long>")


def _lists(rows: list[np.ndarray]) -> pa.Array:
    offsets = np.concatenate([[0], np.cumsum([len(x) for x in rows])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(rows) if rows else np.empty(0, np.int64)))


def verified(spark: SparkSession, docs: DataFrame, nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """The pairs (a, b) of ``nodes`` whose texts' shingles, compared as words, have a similarity of 4/5 or more."""
    pairs = materialized(spark, pairs, "candidates", few=True)
    wanted = pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct()
    wanted = materialized(spark, nodes.select("node", "of").join(wanted, "node", "left_semi"), "wanted", few=True)
    # A text stands for all of its node: they have the same shingles.
    texts = identified(docs).select("of", "text").join(wanted, "of").dropDuplicates(["node"]).select("node", "text")
    texts = materialized(spark, texts, "texts")
    a, b = texts.select(F.col("node").alias("a"), F.col("text").alias("text_a")), texts.select(F.col("node").alias("b"), F.col("text").alias("text_b"))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in parts(batches):
            sides = [batch_texts(batch.column(i)) for i in (2, 3)]
            near, last, own = [], None, set()
            for i, node in enumerate(batch.column(0).to_pylist()):
                left, right = (raw[starts[i] : ends[i]].tobytes() for raw, starts, ends in sides)
                if node != last:
                    last, own = node, set(shingles_of(left))
                other = set(shingles_of(right))
                near.append(5 * len(own & other) >= 4 * len(own | other))
            yield batch.select([0, 1]).filter(pa.array(near, pa.bool_()))

    return pairs.join(a, "a").join(b, "b").select("a", "b", "text_a", "text_b").mapInArrow(compare, "a long, b long")


def linked_nodes(nodes: DataFrame, prints: DataFrame, max_bits: int = 3) -> DataFrame:
    """Pairs (a, b), a < b, of ``nodes`` that the fingerprints ``prints`` (fp, node) link and whose sketches allow them to be
    copies: of one fingerprint each with the smallest, of two that differ in ``max_bits`` bits or fewer the smallest of both.
    """
    first = prints.groupBy("fp").agg(F.min("node").alias("first"))
    equal = prints.join(first, "fp").select(F.col("first").alias("a"), F.col("node").alias("b"))
    side = lambda x: first.select(F.col("fp").alias(x), F.col("first").alias(f"first_{x}"))
    near = links(first.select("fp"), max_bits).join(side("a"), "a").join(side("b"), "b").select(F.least("first_a", "first_b").alias("a"), F.greatest("first_a", "first_b").alias("b"))
    own = lambda x: nodes.select(F.col("node").alias(x), F.struct("n", "bits").alias(f"of_{x}"))
    pairs = equal.union(near).where("a < b").distinct().join(own("a"), "a").join(own("b"), "b")
    return pairs.where(_close("of_a", "of_b")).select("a", "b")


def copies(spark: SparkSession, docs: DataFrame, nodes: DataFrame, prints: DataFrame) -> DataFrame:
    """Pairs (a, b), a < b, of ``nodes`` (node, of, n, head, bits) of a similarity of 4/5 or more that link all copies.

    What the fingerprints ``prints`` (fp, node) link is compared first; the filters after it look between components.
    """
    tried = linked_nodes(nodes, prints)
    postings = nodes.select("node", F.explode("head").alias("shingle")).withColumn("k", F.count("*").over(W.partitionBy("shingle"))).where("k > 1")
    sizes = nodes.select("node", "n", F.size("head").alias("p"), F.element_at("head", -1).alias("last"))
    shared = materialized(spark, postings.join(sizes, "node"), "shared")
    short, long = shared.where(F.col("k") <= LONG).drop("k"), shared.where(F.col("k") > LONG)
    some = not long.isEmpty()
    if some:
        long = materialized(spark, long.join(nodes.select("node", "bits"), "node"), "long")
        tried = tried.union(likely(long)).distinct()
    edges = materialized(spark, verified(spark, docs, nodes, tried), "edges")
    roots = materialized(spark, components(spark, edges), "roots", few=True)
    rooted = lambda rows: rows.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    pairs = short_pairs(rooted(short))
    if some:
        pairs = pairs.union(long_pairs(rooted(long)))
    return edges.union(verified(spark, docs, nodes, counted(pairs)))


def likely(long: DataFrame) -> DataFrame:
    """For each member of long lists the few pairs whose sketches are closest, of those that some random order of a
    list's members brings together."""
    part = F.pmod(F.xxhash64("node", "shingle"), F.ceil(F.col("k") / BLOCK))
    order = W.partitionBy("shingle", "part").orderBy(F.xxhash64("shingle", "node"), "node")
    own = F.struct("node", "n", "bits")
    tries = long.withColumn("part", part).select(own.alias("b"), F.array(*[F.lag(own, i).over(order) for i in range(1, AHEAD + 1)]).alias("others"))
    tries = tries.select("b", F.explode("others").alias("a")).where("a is not null").where(_close("a", "b"))
    share = _apart(F.col("a.bits"), F.col("b.bits")) / (F.col("a.n") + F.col("b.n"))
    tries = tries.select(F.col("a.node").alias("a"), F.col("b.node").alias("b"), share.alias("share")).dropDuplicates(["a", "b"])
    best = F.row_number().over(W.partitionBy("b").orderBy("share", "a"))
    return tries.withColumn("rank", best).where(F.col("rank") <= BEST).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _rest(rows: DataFrame) -> DataFrame:
    """(a, b, rest, both) of pairs: all of the head that ends first has been looked for in the other one; ``rest`` is how
    many shingles follow it, which may be shared."""
    rest = F.when(F.col("a.last") <= F.col("b.last"), F.col("a.n") - F.col("a.p")).otherwise(F.col("b.n") - F.col("b.p"))
    return rows.select(F.least("a.node", "b.node").alias("a"), F.greatest("a.node", "b.node").alias("b"), rest.alias("rest"), (F.col("a.n") + F.col("b.n")).alias("both"))


def short_pairs(short: DataFrame) -> DataFrame:
    """A row for each shingle that the heads of two texts of different roots share, in short lists."""
    side = lambda x: short.select("shingle", F.struct("node", "n", "p", "last", "root").alias(x))
    return _rest(side("a").join(side("b"), "shingle").where("a.node < b.node and a.root <> b.root and 5 * a.n >= 4 * b.n and 5 * b.n >= 4 * a.n"))


def long_pairs(long: DataFrame) -> DataFrame:
    """The same in long lists, of texts whose sketches allow them to be copies.

    Members of a list's largest component are linked already: all members meet only those outside of it, in parts
    that each hold some ``BLOCK`` of the former.
    """
    held = long.groupBy("shingle", "root").agg(F.count("*").alias("held"))
    main = held.groupBy("shingle").agg(F.max_by("root", F.struct("held", "root")).alias("main"))
    rows = long.join(main, "shingle")
    blocks = F.ceil(F.col("k") / BLOCK).cast("long")
    side = lambda rows, x, block: rows.select("shingle", "main", block.alias("block"), F.struct("node", "n", "p", "last", "root", "bits").alias(x))
    left = side(rows, "a", F.pmod(F.xxhash64("node"), blocks))
    right = side(rows.where("root <> main"), "b", F.explode(F.sequence(F.lit(0).cast("long"), blocks - 1))).drop("main")
    met = left.join(right, ["shingle", "block"]).where((F.expr("a.root <> b.root and (a.root = main or a.node < b.node)")) & _close("a", "b"))
    return _rest(met)


def counted(pairs: DataFrame) -> DataFrame:
    """Pairs (a, b) that share as many shingles of their heads as copies must, from a row for each."""
    pairs = pairs.groupBy("a", "b").agg(F.count("*").alias("c"), F.first("rest").alias("rest"), F.first("both").alias("both"))
    return pairs.where("9 * (c + rest) >= 4 * both").select("a", "b")


def similar_classes(spark: SparkSession, docs: DataFrame, rows: DataFrame) -> DataFrame:
    """(node, root, component_id) of each set of shingles of ``rows`` (doc_id, of, fp, node, n, head, bits), those of ``docs``."""
    one = [F.first(c).alias(c) for c in ("n", "head", "bits")]
    nodes = rows.groupBy("node").agg(F.min("doc_id").alias("first_id"), F.min("of").alias("of"), *one)
    nodes = materialized(spark, nodes, "nodes")
    prints = materialized(spark, rows.select("fp", "node").distinct(), "prints", few=True)
    joined = components(spark, copies(spark, docs, nodes, prints))
    linked = nodes.select("node", "first_id").join(joined, "node", "left").withColumn("root", F.coalesce("root", "node"))
    named = linked.groupBy("root").agg(F.min("first_id").alias("component_id"))
    return linked.join(named, "root").select("node", "root", "component_id")


def deduplicated_similar(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """One row of each group of copies (equal texts, or a five-word similarity of 0.8 or more), columns as in ``docs``."""
    rows = materialized(spark, with_heads(docs, common_shingles(docs)), "fingerprints")
    return one_of_each(docs, rows.select("doc_id", "of", "node"), similar_classes(spark, docs, rows), "node")
