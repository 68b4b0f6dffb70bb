"""Document fingerprints as invertible Bloom lookup sketches, by DataFrame functions alone.

A text is cut into paragraphs: at line ends, and inside a line wherever two neighbouring characters are of two fixed
classes.  What is cut where depends on those two characters alone, not on a text's length nor on what stands before, so
an edit changes the paragraphs it touches and no other, and text put in front moves none.  Each distinct paragraph's
64-bit digest goes into three cells, one in each third of the sketch; a cell holds how many digests it got, their
exclusive or, and the exclusive or of their checksums.  Two sketches of one size are subtracted cell by cell: paragraphs
that both versions have cancel.  Peeling then recovers the others: a cell that holds one digest (its checksum fits)
gives it away, it is taken out of its other cells, and so on, all such cells of a round at once.

The fingerprint is the sketch of ``CELLS`` cells with the number of paragraphs; if two fingerprints do not peel, the
difference is larger than they hold.  Then the digests of both are dealt by their value into buckets of some
``BUCKET``, and each bucket gets a sketch of its own, of a size that its digests need at most, up to ``RETRIES`` times
larger with other hashes; a bucket that still has cells left is compared as two sets.  So the recovered difference is
always exact, and the work of a row grows with its paragraphs (times the root of their number for dealing).

Likeness is shared over all distinct paragraphs, from the sizes of both sets and the recovered difference.

Everything of a row is computed in the row, by higher-order functions over arrays.

Defined results: a null text is empty and has no paragraph; two texts without a paragraph are alike (1); a text in which
no two neighbours are of those classes is one paragraph a line; rows of equal doc_id follow one another by the text's
hash; a table of one row is its own next document; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import materialized, only

#: Cells of the fingerprint (a multiple of three), digests in a bucket, how often a bucket is tried again, and how many
#: rounds one try may take.  What fails is tried larger and compared as sets in the end, so none of these cuts a result.
CELLS, BUCKET, RETRIES, ROUNDS = 24, 10, 4, 12
#: A paragraph ends behind a character of BEFORE that is followed by one of LAST.  The classes share no character, so
#: no two such places overlap.
BEFORE, LAST = "gkmvwzGKMVWZ02468.é", "aioyAIOY13579('ü-"
FOUND, CELL = "ARRAY<STRUCT<d: BIGINT, n: BIGINT>>", "ARRAY<STRUCT<n: BIGINT, k: BIGINT, x: BIGINT>>"
_ZERO = "named_struct('n', 0L, 'k', 0L, 'x', 0L)"


def _ranges(first: int, last: int) -> str:
    """A class of other scripts' characters: a run of every small block of letters and of every larger one beyond."""
    small = [(c + first, c + last) for c in range(0x100, 0x1100, 0x20)]
    large = [(c + 32 * first, c + 32 * last) for c in range(0x1100, 0xD800, 0x400)]
    return "".join(f"\\u{a:04x}-\\u{b:04x}" for a, b in small + large)


#: What a paragraph ends with; other scripts are looked up only where a character is of one.
ENDS = rf"[{BEFORE}][{LAST}]|\n|[\u0100-\uffff&&[{_ranges(0, 5)}]][{_ranges(8, 13)}]"


def pieces(text: Column) -> Column:
    """The paragraphs of a text, in order."""
    # A mark (a character that text hardly has; where it does, it ends a paragraph too) is set and split at: both are linear.
    marked = F.regexp_replace(text, F.lit(ENDS), F.lit("$0\u0001"))
    return F.filter(F.split(marked, "\u0001", -1), lambda x: x != "")


def digests(text: Column) -> Column:
    """The distinct digests of a text's paragraphs."""
    return F.array_distinct(F.transform(pieces(text), lambda x: F.xxhash64(x)))


def bound(value: str, name: str, body: str) -> str:
    """``body`` with ``value`` bound to ``name``, so that it is computed once."""
    return f"transform(array({value}), {name} -> {body})[0]"


def _entries(digest_array: str, third: str, seed: str, sign: str = "1L") -> str:
    """Each digest with its sign, its checksum and its cell in each third."""
    return f"transform({digest_array}, d -> named_struct('d', d, 'n', {sign}, 'x', xxhash64(d, {seed}, 3), {_cells('d', third, seed)}))"


def _cells(digest: str, third: str, seed: str) -> str:
    return ", ".join(f"'c{j}', CAST(pmod(xxhash64({digest}, {seed}, {j}), {third}) AS INT)" for j in range(3))


def _sketch(entries: str, third: str) -> list[str]:
    """The three thirds of a sketch, each an array of cells; a digest is looked for in one cell of each alone."""
    add = "named_struct('n', a.n + e.n, 'k', a.k ^ e.d, 'x', a.x ^ e.x)"
    return [f"transform(sequence(0, {third} - 1), c -> aggregate({entries}, {_ZERO}, (a, e) -> CASE WHEN e.c{j} = c THEN {add} ELSE a END))" for j in range(3)]


def _minus(left: str, right: str) -> str:
    return f"zip_with({left}, {right}, (p, q) -> named_struct('n', p.n - q.n, 'k', p.k ^ q.k, 'x', p.x ^ q.x))"


def _peel(cells: list[str], third: str, seed: str) -> str:
    """What peeling recovers (digests with 1 for the left side's, -1 for the right side's), or null if cells are left
    or more than ``ROUNDS`` rounds are needed.

    ``cells`` are the thirds of a difference.  When nothing is left to peel, the cells go, so that the rounds that
    remain have little to carry.
    """
    pure = f"abs(p.n) = 1 AND p.x = xxhash64(p.k, {seed}, 3)"
    found = "array_distinct(concat(" + ", ".join(f"transform(filter(s.t{j}, p -> {pure}), p -> named_struct('d', p.k, 'n', p.n))" for j in range(3)) + "))"
    out = f"transform({found}, o -> named_struct('d', o.d, 'n', o.n, 'x', xxhash64(o.d, {seed}, 3), {_cells('o.d', third, seed)}))"
    take = "named_struct('n', a.n - o.n, 'k', a.k ^ o.d, 'x', a.x ^ o.x)"
    after = ", ".join(f"'t{j}', transform(s.t{j}, (p, i) -> aggregate(outs, p, (a, o) -> CASE WHEN o.c{j} = i THEN {take} ELSE a END))" for j in range(3))
    taken = "concat(s.found, transform(outs, o -> named_struct('d', o.d, 'n', o.n)))"
    clear = " AND ".join(f"forall(s.t{j}, z -> z.n = 0 AND z.k = 0 AND z.x = 0)" for j in range(3))
    none = ", ".join(f"'t{j}', CAST(array() AS {CELL})" for j in range(3))
    over = f"named_struct({none}, 'found', CASE WHEN {clear} THEN s.found END, 'over', true)"
    step = bound(out, "outs", f"CASE WHEN size(outs) = 0 THEN {over} ELSE named_struct({after}, 'found', {taken}, 'over', false) END")
    start = "named_struct(" + ", ".join(f"'t{j}', {x}" for j, x in enumerate(cells)) + f", 'found', CAST(array() AS {FOUND}), 'over', false)"
    return f"aggregate(sequence(1, {ROUNDS}), {start}, (s, r) -> CASE WHEN s.over THEN s ELSE {step} END, s -> CASE WHEN s.over THEN s.found END)"


def _buckets(left: str, right: str, count: str) -> str:
    """The digests of both sides by their value, in two steps: first into some root of ``count`` groups."""
    side = lambda of, test: f"filter({of}, d -> {test})"
    both = lambda l, r, test: f"named_struct('l', {side(l, test)}, 'r', {side(r, test)})"
    groups = f"transform(sequence(0, w - 1), g -> {both(left, right, f'pmod(d, {count}) div w = g')})"
    parts = f"flatten(transform({groups}, (y, g) -> transform(sequence(0, w - 1), j -> {both('y.l', 'y.r', f'pmod(d, {count}) = g * w + j')})))"
    return bound(f"CAST(ceil(sqrt({count})) AS INT)", "w", parts)


def difference(left: str, right: str, left_cells: str, right_cells: str) -> Column:
    """The paragraphs that two versions do not share (digest, 1 or -1 by side): peeled from the fingerprints'
    difference, else from larger sketches of parts of both.

    ``left`` and ``right`` name columns of digests, ``*_cells`` their fingerprints' cells.
    """
    third = CELLS // 3
    first = bound(_minus(left_cells, right_cells), "m", _peel([f"slice(m, {j * third + 1}, {third})" for j in range(3)], str(third), "0"))
    signed = f"concat({_entries('q.l', 'm', 't')}, {_entries('q.r', 'm', 't', '-1L')})"
    larger = bound("(CAST((size(q.l) + size(q.r)) / 2 AS INT) + 2) * t", "m", bound(signed, "y", _peel(_sketch("y", "m"), "m", "t")))
    sets = "concat(transform(array_except(q.l, q.r), d -> named_struct('d', d, 'n', 1L)), transform(array_except(q.r, q.l), d -> named_struct('d', d, 'n', -1L)))"
    tried = f"aggregate(sequence(1, {RETRIES}), CAST(NULL AS {FOUND}), (f, t) -> CASE WHEN f IS NULL THEN {larger} ELSE f END, f -> coalesce(f, {sets}))"
    solved = f"CASE WHEN size(q.l) + size(q.r) = 0 THEN CAST(array() AS {FOUND}) ELSE {tried} END"
    dealt = bound(f"greatest(1, CAST(ceil((size({left}) + size({right})) / {BUCKET}) AS INT))", "parts", f"flatten(transform({_buckets(left, right, 'parts')}, q -> {solved}))")
    return F.expr(f"coalesce({first}, {dealt})")


def cells_of(digest_array: str) -> Column:
    third = str(CELLS // 3)
    return F.expr(bound(_entries(digest_array, third, "0"), "y", f"concat({', '.join(_sketch('y', third))})"))


def printed(cells: str, digest_array: str) -> Column:
    """A sketch as text: paragraphs, then each cell's count, digests and checksums in hexadecimal."""
    return F.expr(f"concat_ws('.', transform({cells}, z -> concat_ws(':', hex(z.n), hex(z.k), hex(z.x))), CAST(size({digest_array}) AS STRING))")


def likeness(left: str, right: str, differing: Column) -> Column:
    """Shared over all distinct paragraphs: of ``a`` and ``b`` with ``d`` in one only, (a + b - d) / (a + b + d)."""
    both = (F.size(left) + F.size(right)).cast("double")
    return F.when(both == 0, 1.0).otherwise((both - differing) / (both + differing))


def neighbours(rows: DataFrame) -> DataFrame:
    """(key, doc_id, next_key, need) of (key, doc_id, of, n): each row's next in descending doc_id, after the last the first.

    Ids are range-partitioned and sorted; a row's place is its number in its partition plus the rows of the partitions
    before, so no task ever sees all rows, only one count per partition.
    """
    order = [F.col("doc_id").desc_nulls_last(), F.col("of").desc(), F.col("key")]
    n = max(rows.sparkSession.sparkContext.defaultParallelism, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    # Written, so that numbers and counts come from the same ranges.
    dealt = materialized(rows.sparkSession, rows.repartitionByRange(n, *order).withColumn("part", F.spark_partition_id()), "order", few=True)
    placed = dealt.withColumn("at", F.row_number().over(W.partitionBy("part").orderBy(*order)))
    counts = dealt.groupBy("part").agg(F.count("*").alias("size"))
    before = F.coalesce(F.sum("size").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    counts = counts.select("part", before.alias("before"), F.sum("size").over(W.partitionBy(F.lit(1))).alias("all"))
    placed = placed.join(counts, "part").select("key", "doc_id", "n", "all", (F.col("before") + F.col("at") - 1).alias("place"))
    follower = placed.select(F.col("key").alias("next_key"), F.pmod(F.col("place") - 1, F.col("all")).alias("place"))
    return placed.join(follower, "place").select("key", "doc_id", "next_key", F.floor(F.col("n") / 3).cast("int").alias("need"))


def fingerprint_report(docs: DataFrame) -> DataFrame:
    """Fingerprints of each text and of its edited version, their likeness, and the digests of the paragraphs that the
    edit ``removed`` and ``added``, as peeling recovers them; per row of ``docs`` (doc_id, text).

    The edited text ends with what the next document begins with.  Rows are keyed by their place in the scan, which is
    the same in every run over the same files (``docs`` should be a table, or a plan that deals its rows alike each
    time; write it first otherwise); the text is shuffled once by that key and read twice from there, and a
    document hands its neighbour only the characters needed and its own digests.
    """
    own = only(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    own = own.withColumn("key", F.monotonically_increasing_id())
    order = neighbours(own.select("key", "doc_id", F.xxhash64("text").alias("of"), F.char_length("text").alias("n")))
    # Both joins need the same two columns of the same exchange, so Spark shuffles the text once.
    gives = order.select(F.col("next_key").alias("key"), F.col("key").alias("to"), "doc_id", "need")
    texts = own.select("key", "text")
    given = texts.hint("merge").join(gives.hint("merge"), "key").select(F.col("to").alias("key"), "doc_id", F.expr("substring(text, 1, need)").alias("tail"), digests(F.col("text")).alias("next_digests"))
    rows = texts.hint("merge").join(given.hint("merge"), "key")
    rows = rows.withColumn("n_chars", F.char_length("text").cast("long"))
    rows = rows.withColumn("edited", F.concat(F.expr("substring(text, 1, CAST(n_chars - floor(n_chars / 3) AS INT))"), "tail"))
    rows = rows.select("doc_id", "n_chars", F.sha2(F.encode("edited", "UTF-8"), 256).alias("edited_sha256"), digests(F.col("text")).alias("a"), digests(F.col("edited")).alias("b"), F.col("next_digests").alias("c"))
    rows = rows.withColumns({f"{x}_cells": cells_of(x) for x in "abc"})
    rows = rows.withColumns({"d_edited": difference("a", "b", "a_cells", "b_cells"), "d_next": F.size(difference("a", "c", "a_cells", "c_cells"))})
    side = lambda n: F.array_sort(F.transform(F.filter("d_edited", lambda x: x["n"] == n), lambda x: x["d"]))
    return rows.select(
        "doc_id", "n_chars", "edited_sha256", printed("a_cells", "a").alias("fingerprint"), printed("b_cells", "b").alias("edited_fingerprint"),
        likeness("a", "b", F.size("d_edited")).alias("near_edited"), likeness("a", "c", F.col("d_next")).alias("near_next"),
        side(1).alias("removed"), side(-1).alias("added"),
    )
