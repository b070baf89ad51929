"""Near-duplicate groups by min-max hashing, banding and exact confirmation.

Each permutation of the shingles gives two signature values, the smallest and
the largest image, so a signature of given length takes half the hash
evaluations, and both values agree between two sets with a probability equal to
their Jaccard similarity. Values are grouped into bands; equal bands make
candidates.

1. Texts with the same shingle set become one class, its smallest id stands for
   it; only these representatives are banded.
2. In each bucket of a band the smallest id is the pivot, and every member is
   compared with the pivot only: as many pairs as members. A candidate pair is
   confirmed on the full shingle sets, recomputed from the texts.
3. Confirmed links give components. A member that is not linked with its pivot
   may still belong with another member. Jaccard distance is a metric, so such
   a member can only be linked to a member that is linked with the pivot if its
   own similarity to the pivot is high enough; it is compared with those if it
   lies in another component than they do. The members that are not linked with
   the pivot are compared with each other where they lie in different
   components.

A group of thousands of copies thus costs one comparison a member. Where many
texts are close without being linked, members are compared in blocks: a task
holds two blocks and returns only as many links as connect what is linked, so
pairs are not rows and no bucket lies in one task.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pagecast.cluster import Written, ship
from pagecast.llm.components import connected_components
from pagecast.llm.words import mix, shingle_set, strings, unused, utf8, worker_for


#: Ids of texts to compare are broadcast up to this number (16 MB); more are left to the shuffle joins.
BROADCAST_IDS = 2_000_000


#: Members of a bucket, and bytes of their texts, that one task holds from either side, about.
BLOCK, BLOCK_BYTES = 256, 1 << 22
#: Blocks of one side that a task meets with all blocks of the other.
BLOCKS_TOGETHER = 8
#: Pairs with one pivot that one task compares.
PAIRS_TOGETHER = 2000
#: Shingles times permutations whose images are held at once.
IMAGES = 1 << 16


@dataclass(frozen=True)
class DedupPlan:
    shingle_words: int = 5
    #: similarity = intersection / union >= percent / 100
    percent: int = 80
    permutations: int = 96  # two signature values each
    rows: int = 6  # of a band; 32 bands find a pair at 0.8 with 1 - 6e-5


def _multipliers(count: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(2024)
    draw = lambda: rng.integers(1, 2**63, count, dtype=np.uint64)
    return draw() * np.uint64(2) + np.uint64(1), draw()


def signature(shingles: np.ndarray, plan: DedupPlan) -> np.ndarray:
    """Smallest and largest value of each permutation, side by side."""
    scale, shift = _MULTIPLIERS.setdefault(plan.permutations, _multipliers(plan.permutations))
    out = np.empty((plan.permutations, 2), np.uint64)
    some = max(1, min(plan.permutations, IMAGES // max(1, len(shingles))))
    with np.errstate(over="ignore"):
        for k in range(0, plan.permutations, some):
            image = shingles * scale[k : k + some, None]
            image += shift[k : k + some, None]
            image.min(axis=1, out=out[k : k + some, 0])
            image.max(axis=1, out=out[k : k + some, 1])
    return out.reshape(-1)


_MULTIPLIERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def bands(shingles: np.ndarray, plan: DedupPlan) -> np.ndarray:
    """One 64-bit key per band (the band's number is part of it)."""
    values = signature(shingles, plan)
    count = len(values) // plan.rows
    table = values[: count * plan.rows].reshape(count, plan.rows)
    key = mix(np.arange(1, count + 1, dtype=np.uint64))
    for r in range(plan.rows):
        key = mix(key ^ table[:, r])
    return key


def _summaries(docs: DataFrame, plan: DedupPlan) -> DataFrame:
    """(doc_id, n_shingles, n_bytes, digest, bands); a text without words has no digest."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in worker_for("shingles", batches):
            sizes, lengths, digests, keys = [], [], [], []
            last: tuple[str | None, tuple] = (None, ())
            for text in strings(batch.column(1)):
                if text is None or text != last[0]:
                    found = shingle_set(text, plan.shingle_words)
                    if len(found):
                        # a shorter set and a longer one never share a digest
                        last = (text, (len(found), len(utf8(text)), xxhash.xxh3_128_digest(found.tobytes()), bands(found, plan).view(np.int64)))
                    else:
                        last = (text, (0, 0, None, None))
                for column, value in zip((sizes, lengths, digests, keys), last[1]):
                    column.append(value)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(sizes, pa.int64()), pa.array(lengths, pa.int64()), pa.array(digests, pa.binary()), pa.array(keys, pa.list_(pa.int64()))],
                ["doc_id", "n_shingles", "n_bytes", "digest", "bands"],
            )

    return docs.mapInArrow(run, "doc_id bigint, n_shingles bigint, n_bytes bigint, digest binary, bands array<bigint>")


def _confirmed(pairs: DataFrame, docs: DataFrame, plan: DedupPlan) -> DataFrame:
    """pairs(a, b) -> (a, b, linked, close) from the full shingle sets.

    Texts travel, not sets: they compress to a third of the sets' size. Rows
    are small in number (a few for each member). A hot pivot's pairs are dealt
    over tasks by a salt that follows their number, and its text goes to each.
    """

    def side(name: str, ids: DataFrame) -> DataFrame:
        """The texts of the ids, beside whatever else ``ids`` has."""
        if ids.count() <= BROADCAST_IDS:
            ids = F.broadcast(ids)
        return docs.select(F.col("doc_id").alias(name), F.col("text").alias(f"{name}_text")).join(ids, name)

    # a member that is linked with z, where z is linked with the pivot, is at least this close
    reach = 2 * plan.percent - 100

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple[str | None, np.ndarray] = (None, np.empty(0, np.uint64))
        for batch in worker_for("shingles", batches):
            linked, close = [], []
            for left, right in zip(batch.column(2), batch.column(3)):
                left, right = left.as_py(), right.as_py()
                if right != held[0]:
                    held = (right, shingle_set(right, plan.shingle_words))
                x, y = shingle_set(left, plan.shingle_words), held[1]
                both = len(np.intersect1d(x, y, assume_unique=True))
                union = len(x) + len(y) - both
                linked.append(both > 0 and 100 * both >= plan.percent * union)
                close.append(100 * both >= reach * union)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(linked, pa.bool_()), pa.array(close, pa.bool_())], ["a", "b", "linked", "close"])

    pivots = pairs.groupBy("b").agg(F.ceil(F.count("*") / PAIRS_TOGETHER).alias("shares"))
    dealt = pairs.join(pivots, "b").withColumn("salt", F.pmod(F.xxhash64("a"), F.col("shares"))).drop("shares")
    everywhere = side("b", pivots).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("shares") - 1))).drop("shares")
    both = dealt.join(side("a", pairs.select("a").distinct()), "a").join(everywhere, ["b", "salt"]).select("a", "b", "a_text", "b_text")
    compared = both.mapInArrow(run, "a bigint, b bigint, linked boolean, close boolean")
    # rows that share an id are one node: one of their texts is enough
    return compared.groupBy("a", "b").agg(F.max("linked").alias("linked"), F.max("close").alias("close"))


class _Links:
    """The pairs compared so far and the components of the links among them."""

    def __init__(self, docs: DataFrame, plan: DedupPlan, lengths: DataFrame):
        self.docs, self.plan = docs, plan
        self.lengths = lengths  # (id, n_bytes) of all members
        self.checked: list[Written] = []
        self.component: Written | None = None

    def compare(self, pairs: DataFrame) -> None:
        """Compare the pairs (a, b) that have not been compared yet."""
        pairs = pairs.distinct()
        for old in self.checked:
            pairs = pairs.join(old.df.select("a", "b"), ["a", "b"], "left_anti")
        new = Written(pairs, "dedup-pairs")
        self.add(_confirmed(new.df, self.docs, self.plan))
        new.drop()

    def add(self, verdicts: DataFrame) -> None:
        self.checked.append(Written(verdicts, "dedup-checked"))
        if self.component is not None:
            self.component.drop()
        self.component = connected_components(self.verdicts().where("linked").select("a", "b"))

    def verdicts(self) -> DataFrame:
        return reduce(DataFrame.unionByName, [c.df for c in self.checked])

    def placed(self, rows: DataFrame, column: str, name: str) -> DataFrame:
        """``rows`` with the component of a column's id (the id itself without links)."""
        of = self.component.df.select(F.col("id").alias(column), F.col("component").alias("_c"))
        return rows.join(of, column, "left").withColumn(name, F.coalesce("_c", column)).drop("_c")

    def compare_groups(self, left: DataFrame, right: DataFrame | None, keys: list[str], many: int) -> None:
        """Compare, in each group, all left members (keys, id) with all right
        ones, or with each other without ``right``.

        Few pairs are compared one by one, each once. Many are compared in
        blocks of members: a task gets the texts of two blocks, compares them
        exactly and returns no more links than connect what is linked, so pairs
        are never rows. Blocks are bounded in members and in bytes; a large
        group's left blocks are dealt over tasks by a salt that follows their
        number, and its right blocks go to each.
        """
        other = left if right is None else right

        def size(df: DataFrame, name: str) -> DataFrame:
            blocks = F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("n_bytes") / BLOCK_BYTES), F.lit(1))
            return df.join(self.lengths, "id").groupBy(*keys).agg(F.count("*").alias(name), blocks.alias(f"{name}_blocks"))

        sizes = Written(size(left, "n").join(size(other, "m"), keys).withColumn("shares", F.ceil(F.col("n_blocks") / BLOCKS_TOGETHER)), "dedup-sizes")
        total = sizes.df.agg(F.sum(F.col("n") * F.col("m"))).first()[0] or 0
        if not total:
            sizes.drop()
            return
        renamed = other.select(*keys, F.col("id").alias("z"))
        if total <= many:
            self.compare(left.join(renamed, keys).where("id <> z").select(F.greatest("id", "z").alias("a"), F.least("id", "z").alias("b")))
            sizes.drop()
            return
        ids = Written(left.select("id").unionByName(other.select("id")).distinct(), "dedup-ids")
        wanted = F.broadcast(ids.df) if ids.df.count() <= BROADCAST_IDS else ids.df
        texts = self.docs.join(wanted, F.col("doc_id") == F.col("id"), "left_semi").select(F.col("doc_id").alias("id"), "text")

        def blocks(df: DataFrame, count: str, name: str) -> DataFrame:
            cut = df.join(sizes.df, keys).withColumn(f"{name}_block", F.pmod(F.xxhash64("id"), F.col(f"{count}_blocks"))).select(*keys, "shares", "id", f"{name}_block")
            return cut.join(texts, "id").groupBy(*keys, "shares", f"{name}_block").agg(F.collect_list(F.struct("id", "text")).alias(name))

        dealt = blocks(left, "n", "x").withColumn("salt", F.pmod(F.col("x_block"), F.col("shares"))).drop("shares")
        everywhere = blocks(other, "m", "y").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("shares") - 1))).drop("shares")
        met = dealt.join(everywhere, [*keys, "salt"])
        if right is None:
            met = met.where("x_block <= y_block")
        merged, plan = right is not None, self.plan

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in worker_for("shingles", batches):
                for k in range(len(batch)):
                    links = _forest(batch.column(0)[k].as_py(), batch.column(1)[k].as_py(), plan, merged)
                    yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in links], pa.int64()), pa.array([p[1] for p in links], pa.int64())], ["a", "b"])

        found = met.select("x", "y").mapInArrow(run, "a bigint, b bigint")
        self.add(found.distinct().select("a", "b", F.lit(True).alias("linked"), F.lit(True).alias("close")))
        sizes.drop()
        ids.drop()


def _forest(xs: list[dict], ys: list[dict], plan: DedupPlan, merged: bool) -> list[tuple[int, int]]:
    """Links (larger id, smaller id) that connect the members of two blocks as
    all links between them do. ``merged``: the second block's members lie in
    one component already."""
    sets = {m["text"]: shingle_set(m["text"], plan.shingle_words) for m in [*xs, *ys]}
    union, percent = np.unique(np.concatenate(list(sets.values()))), plan.percent

    def bits(members: list[dict]) -> tuple[np.ndarray, np.ndarray]:
        table = np.zeros((len(members), -(-len(union) // 64) * 8), np.uint8)
        for row, m in zip(table, members):
            held = np.zeros(table.shape[1] * 8, bool)
            held[np.searchsorted(union, sets[m["text"]])] = True
            row[:] = np.packbits(held)
        return table.view(np.uint64), np.array([len(sets[m["text"]]) for m in members])

    (x, x_size), (y, y_size) = bits(xs), bits(ys)
    root = {m["id"]: m["id"] for m in [*xs, *ys]}

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    if merged:
        for m in ys:
            root[find(m["id"])] = find(ys[0]["id"])
    out = []
    for i, m in enumerate(xs):
        both = np.bitwise_count(x[i][None, :] & y).sum(1).astype(np.int64)
        for j in np.flatnonzero((both > 0) & (100 * both >= percent * (x_size[i] + y_size - both))):
            a, b = m["id"], ys[j]["id"]
            if find(a) != find(b):
                root[find(a)] = find(b)
                out.append((max(a, b), min(a, b)))
    return out


def near_duplicates(df: DataFrame, plan: DedupPlan = DedupPlan(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id, kept: one row per input row.

    Two texts are linked if 100 * |intersection| >= percent * |union| of their
    sets of word shingles; a text of fewer words than a shingle is one shingle.
    ``component_id`` is the smallest id that links lead to. A null or empty
    text, or one without words, has no shingles and is linked with nothing. A
    row with a null id takes part in nothing: its component is null and it is
    kept. Rows that share an id are one node. An empty table gives an empty
    result; other columns are not read.
    """
    spark = df.sparkSession
    ship(spark)
    docs = df.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    known = Written(_summaries(docs, plan), "dedup-summaries")
    some = known.df.where("digest is not null and doc_id is not null")
    # copies share their bands, so any of them will do
    classes = Written(some.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.first("bands").alias("bands"), F.max("n_bytes").alias("n_bytes")), "dedup-classes")
    many = classes.df.count()

    banded = classes.df.select(F.col("rep").alias("id"), F.explode("bands").alias("bucket")).distinct()
    several = banded.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1").select("bucket")
    active = Written(banded.join(several, "bucket"), "dedup-buckets")
    # an id with several texts has the lengths of all
    links = _Links(docs, plan, classes.df.groupBy(F.col("rep").alias("id")).agg(F.sum("n_bytes").alias("n_bytes")))

    # every member with its bucket's pivot
    first = active.df.groupBy("bucket").agg(F.min("id").alias("pivot"))
    met = Written(active.df.join(first, "bucket").where("id > pivot"), "dedup-met")
    links.compare(met.df.select(F.col("id").alias("a"), F.col("pivot").alias("b")))
    seen = Written(met.df.join(links.verdicts().select(F.col("a").alias("id"), F.col("b").alias("pivot"), "linked", "close"), ["id", "pivot"]), "dedup-seen")
    # members that are close to the pivot, with those that are linked with it
    apart = links.placed(links.placed(seen.df.where("not linked and close"), "id", "own"), "pivot", "theirs").where("own <> theirs")
    apart = Written(apart.select("bucket", "pivot", "id"), "dedup-apart")
    near = seen.df.where("linked").select("bucket", "pivot", "id").join(apart.df.select("bucket").distinct(), "bucket", "left_semi")
    links.compare_groups(apart.df, near, ["bucket", "pivot"], many)
    # members that are not linked with the pivot, with each other, where they lie in different components
    rest = Written(links.placed(seen.df.where("not linked").select("bucket", "id"), "id", "own"), "dedup-rest")
    going = rest.df.groupBy("bucket").agg(F.min("own").alias("least"), F.max("own").alias("most")).where("least <> most").select("bucket")
    going = Written(rest.df.join(going, "bucket").select("bucket", "id"), "dedup-going")
    links.compare_groups(going.df, None, ["bucket"], many)
    for old in (active, met, seen, apart, rest, going):
        old.drop()

    member = some.select("digest", F.col("doc_id"), "n_shingles").join(classes.df.select("digest", "rep"), "digest")
    # ids that share a class are linked too; so are classes that share an id
    placed = links.placed(member, "rep", "component").select("doc_id", "component", "n_shingles")
    rest = known.df.where("digest is null or doc_id is null").select("doc_id", F.col("doc_id").alias("component"), "n_shingles")
    out = placed.unionByName(rest)
    return out.select(F.col("doc_id").alias(id_col), "n_shingles", F.col("component").alias("component_id"), F.coalesce(F.col("doc_id") == F.col("component"), F.lit(True)).alias("kept"))


def keep_one(df: DataFrame, plan: DedupPlan = DedupPlan(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``df`` with one document of each group of near-duplicates, the one with
    the smallest id; of rows that repeat its id, one. Rows with a null id, and
    texts without words, stay. Columns are those of ``df``."""
    own = unused("_dup_id", df)
    found = Written(near_duplicates(df, plan, id_col, text_col).select(F.col(id_col).alias(own), F.col("kept").alias("kept")), "dedup-verdicts")
    gone = found.df.where("not kept").select(own).distinct()
    if gone.count() <= BROADCAST_IDS:
        gone = F.broadcast(gone)
    out = df.join(gone, df[id_col] == F.col(own), "left_anti")
    repeated = found.df.where(F.col("kept") & F.col(own).isNotNull()).groupBy(own).count().where("count > 1").select(own)
    if repeated.limit(1).count():
        at = out[id_col] == F.col(own)
        out = out.join(repeated, at, "left_anti").unionByName(out.join(repeated, at, "left_semi").dropDuplicates([id_col]))
    return out


ORACLE = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
    ELSE list_distinct([array_to_string(w[i:i + 3], ' ') for i in range(1, len(w) - 2)]) END AS s FROM words
), shingles AS (
  SELECT doc_id, unnest(s) AS x FROM sets
), links AS (
  SELECT p.doc_id AS a, q.doc_id AS b FROM shingles p JOIN shingles q ON p.x = q.x AND p.doc_id < q.doc_id
  JOIN sets ps ON ps.doc_id = p.doc_id JOIN sets qs ON qs.doc_id = q.doc_id
  GROUP BY p.doc_id, q.doc_id, len(ps.s), len(qs.s) HAVING 100 * count(*) >= 80 * (len(ps.s) + len(qs.s) - count(*))
), arcs AS (
  SELECT a, b FROM links UNION ALL SELECT b, a FROM links
), reach(a, b) AS (
  SELECT doc_id, doc_id FROM sets UNION SELECT r.a, e.b FROM reach r JOIN arcs e ON r.b = e.a
), lowest AS (
  SELECT a AS doc_id, min(b) AS component_id FROM reach GROUP BY a
)
SELECT doc_id, len(s)::BIGINT AS n_shingles, component_id, doc_id = component_id AS kept FROM sets JOIN lowest USING (doc_id)
"""
