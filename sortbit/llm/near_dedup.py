"""Near duplicates by an inverted join on the coordinates of min-wise signatures.

1. Rows with equal shingle sets become one class, named by its least id.
2. Every class is posted under each (coordinate, value) of its signature. Two classes
   with at least `match` equal coordinates of `size` must meet in the postings of their
   `shared - match + 1` rarest shared coordinates (the prefix). Only these lists are merged;
   the long ones are skipped and looked up in the signatures of what the short ones bring together.
3. In each posting list the class with the most list mates overall is the leader. Members
   that collide with it in `match` coordinates are confirmed against it on their full sets.
4. What leaders cannot show is searched whole. Classes whose lists have the same foremost
   leader form a home; in a home that still holds several components, each class outside
   the leader's component is merged with all others, blocks against blocks. In a list that
   holds several homes, classes of different homes and components are merged likewise, each
   pair only in the first list, by rarity, that it shares. A block pair counts collisions
   coordinate by coordinate and drops the pairs that the coordinates left cannot bring to
   `match`; it puts out the classes with a collision partner (no pairs), and those meet again
   with their full sets, where links are confirmed and reduced to a spanning forest.

So groups of thousands of copies cost one row each for their leader, no list is ever
turned into all its pairs, and no partner is dropped. A block holds at most `BLOCK` classes
and, by its longest text, at most about `BLOCK_HASHES` shingles. A link of exactly 75 % has
about one chance in a million to match in fewer than 21 of 48 coordinates; that is the only loss.

Null and empty texts have no shingle: they are classes of their own, linked with nothing.
Rows that repeat an id are one document: they are linked with each other, whatever their
texts, and stay or go together. Rows without an id are linked with nothing of their own, have no
component and stay. No rows: no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import keep, ship, text_chunks
from .components import components
from .shingles import MinWise, fingerprint, shingle_sets, similar

#: Classes in one block of a block-against-block comparison, and shingles where its texts are long.
BLOCK, BLOCK_HASHES = 256, 1 << 22
#: Ids that are sent to every executor rather than shuffled.
BROADCAST_IDS = 1_000_000


def signatures(docs: DataFrame, size: int, seed: int) -> DataFrame:
    """(id, n_shingles, print, sig): print is the set's fingerprint, sig holds coordinate << 32 | value."""
    ship(docs.sparkSession)

    def run(batches):
        wise = MinWise(size, seed)
        place = np.arange(size, dtype=np.int64) << 32
        for batch in text_chunks(batches):
            sets = shingle_sets(batch.column("text"))
            some = [s for s in sets if len(s)]
            keys = iter(wise.signatures(some).astype(np.int64) + place)
            yield pa.record_batch(
                {
                    "id": batch.column("id"),
                    "n_shingles": pa.array([len(s) for s in sets], pa.int64()),
                    "print": pa.array([fingerprint(s) if len(s) else None for s in sets], pa.binary()),
                    "sig": pa.array([next(keys) if len(s) else None for s in sets], pa.list_(pa.int64())),
                }
            )

    return docs.mapInArrow(run, "id long, n_shingles long, print binary, sig array<long>")


def set_table(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """(id, shingles) of the given ids, written. shingles: sorted 64-bit hashes, as bytes."""
    few = ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    some = docs.join(F.broadcast(ids) if few else ids, "id", "left_semi")

    def run(batches):
        for batch in text_chunks(batches):
            yield pa.record_batch({"id": batch.column("id"), "shingles": pa.array([s.tobytes() for s in shingle_sets(batch.column("text"))], pa.binary())})

    return keep(some.mapInArrow(run, "id long, shingles binary"))


def confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets are similar."""

    def run(batches):
        for batch in text_chunks(batches, "sa", 8 << 20):
            ok = [similar(np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64), percent) for x, y in zip(batch.column("sa"), batch.column("sb"), strict=True)]
            yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    one, two = (sets.select(F.col("id").alias(k), F.col("shingles").alias(f"s{k}")) for k in ("a", "b"))
    return pairs.join(one, "a").join(two, "b").select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long")


def blocks(members: DataFrame, group: str) -> DataFrame:
    """Deals each group's members out so that every minor one meets every member in one block pair.

    members: group, id, minor, n_minor, n_all, most (the longest set's size) and others; adds bi, bj and side (0: minor, 1: any).
    """
    members = members.withColumn("rows", F.greatest(F.lit(1), F.least(F.lit(BLOCK), F.floor(BLOCK_HASHES / F.greatest("most", F.lit(1))))))
    part = lambda n: F.ceil(F.col(n) / F.col("rows")).cast("int")
    own = lambda n: F.pmod(F.xxhash64("id"), part(n)).cast("int")
    left = members.where("minor").withColumn("bi", own("n_minor")).withColumn("bj", F.explode(F.sequence(F.lit(0), part("n_all") - 1))).withColumn("side", F.lit(0))
    right = members.withColumn("bj", own("n_all")).withColumn("bi", F.explode(F.sequence(F.lit(0), part("n_minor") - 1))).withColumn("side", F.lit(1))
    return left.unionByName(right)


def _least(items: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Enough of the pairs to join what all of them join."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    out = []
    for x, y in items:
        if (p := root(x)) != (q := root(y)):
            parent[p] = q
            out.append((x, y))
    return out


def _pairs(found: list[tuple[int, int]]) -> pa.Table:
    columns = list(zip(*found, strict=True)) or [(), ()]
    return pa.table({"a": pa.array(columns[0], pa.int64()), "b": pa.array(columns[1], pa.int64())})


def intersections(one: list[np.ndarray], two: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections of two lists of sets: products of 0/1 matrices over the members that recur."""
    out = np.zeros((len(one), len(two)), np.float32)
    names, where = np.unique(np.concatenate([*one, *two]), return_inverse=True)
    recur = np.bincount(where, minlength=len(names)) > 1
    place = np.cumsum(recur) - 1
    owner = np.repeat(np.arange(len(one) + len(two)), [len(s) for s in (*one, *two)])
    held = recur[where]
    column, row = place[where[held]], owner[held]
    order = np.argsort(column, kind="stable")
    column, row = column[order], row[order]
    step = 4096
    for at in range(0, int(recur.sum()), step):
        low, high = np.searchsorted(column, [at, at + step])
        x = np.zeros((len(one) + len(two), step), np.float32)
        x[row[low:high], column[low:high] - at] = 1
        out += x[: len(one)] @ x[len(one) :].T
    return out


def collisions(a: np.ndarray, b: np.ndarray, alive: np.ndarray, match: int, earlier: np.ndarray | None = None) -> np.ndarray:
    """Which of the pairs `alive` have `match` equal coordinates, for two blocks of signatures (one row each).

    A pair is dropped as soon as the coordinates left cannot bring it to `match`. earlier: for
    each row of a, the coordinates whose list comes before this one; pairs equal in one of them
    belong to that list.
    """
    size, alive = a.shape[1], alive.copy()
    count = np.zeros(alive.shape, np.int16)
    for c in range(size):
        same = a[:, c][:, None] == b[:, c][None, :]
        count += same
        if earlier is not None:
            alive &= ~(same & earlier[:, c][:, None])
        left = size - 1 - c
        if left < match:
            alive &= count >= match - left
            if not alive.any():
                break
    return alive


def colliding(members: DataFrame, group: str, match: int, percent: int, across: bool) -> DataFrame:
    """(group, bi, bj, side, id, home, component): the members of each block pair with a partner that `match` coordinates share.

    across: partners have different homes, and count in the first list alone that the two share
    (keys: a member's prefix, the rarest first). Sets whose sizes alone rule a link out are no partners.
    """
    held = [group, "bi", "bj", "side", "id", "home", "component"]

    def run(table: pa.Table) -> pa.Table:
        side, home, comp, n = (table.column(c).to_numpy() for c in ("side", "home", "component", "n"))
        sig = np.array(table.column("sig").to_pylist(), np.int64)
        a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        if not len(a) or not len(b):
            return table.select(held).slice(0, 0)
        alive = (comp[a][:, None] != comp[b][None, :]) & (100 * np.minimum(n[a][:, None], n[b][None, :]) >= percent * np.maximum(n[a][:, None], n[b][None, :]))
        earlier = None
        if across:
            alive &= home[a][:, None] != home[b][None, :]
            earlier = np.zeros((len(a), sig.shape[1]), bool)
            here = table.column(group)[0].as_py()
            for row, keys in enumerate(table.column("keys").take(pa.array(a)).to_pylist()):
                earlier[row, [k >> 32 for k in keys[: keys.index(here)]]] = True
        hit = collisions(sig[a], sig[b], alive, match, earlier)
        return table.select(held).take(pa.array(np.concatenate([a[hit.any(axis=1)], b[hit.any(axis=0)]])))

    more = ["keys"] if across else []
    dealt = blocks(members, group).select(*held, "sig", "n", *more)
    kind = ", ".join(f"{c} {'int' if c in ('bi', 'bj', 'side') else 'long'}" for c in held)
    return dealt.groupBy(group, "bi", "bj").applyInArrow(run, kind)


def linked_in_blocks(found: DataFrame, sets: DataFrame, group: str, percent: int) -> DataFrame:
    """Links (a, b) between the components of a block pair, confirmed on full sets: a spanning forest of them."""

    def run(table: pa.Table) -> pa.Table:
        side, ids, comp = (table.column(c).to_numpy() for c in ("side", "id", "component"))
        every = [np.frombuffer(x.as_py(), np.uint64) for x in table.column("shingles")]
        a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        if not len(a) or not len(b):
            return _pairs([])
        both = intersections([every[i] for i in a], [every[i] for i in b]).astype(np.int64)
        size = np.array([len(s) for s in every])
        union = size[a][:, None] + size[b][None, :] - both
        x, y = np.nonzero((100 * both >= percent * union) & (comp[a][:, None] != comp[b][None, :]))
        _, one = np.unique(np.column_stack([comp[a[x]], comp[b[y]]]), axis=0, return_index=True)  # one link for two components
        edges = _least(list(zip(comp[a[x[one]]].tolist(), comp[b[y[one]]].tolist(), strict=True)))
        return _pairs(edges)

    return found.join(sets, "id").groupBy(group, "bi", "bj").applyInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", percent: int = 75, size: int = 48, match: int = 21, seed: int = 5) -> DataFrame:
    """(id, n_shingles, component_id, kept) for every row; the id must be a whole number."""
    docs = docs.select(F.col(id_col).cast("long").alias("id"), "text")
    rows = keep(signatures(docs, size, seed))
    classes = keep(rows.where("sig is not null and id is not null").groupBy("print").agg(F.min("id").alias("id"), F.any_value("sig").alias("sig"), F.any_value("n_shingles").alias("n")))

    posted = classes.select("id", F.explode("sig").alias("key"))
    shared = keep(posted.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"))
    lists = posted.join(shared, "key").groupBy("id").agg(F.sort_array(F.collect_list(F.struct("n", "key"))).alias("keys"), F.sum("n").alias("mates"))
    prefix = keep(lists.where(F.size("keys") >= match).select("id", "mates", F.slice("keys.key", 1, F.size("keys") - (match - 1)).alias("keys")))
    member = prefix.select("id", "mates", F.explode("keys").alias("key"))
    leaders = keep(member.groupBy("key").agg(F.max_by("id", F.struct("mates", -F.col("id"))).alias("leader"), F.max("mates").alias("lead"), F.count("*").alias("n")).where("n > 1").drop("n"))
    listed = keep(member.join(leaders, "key").select("key", "id", "leader", "lead"))

    sig = classes.join(listed.select("id").distinct(), "id", "left_semi").select("id", "sig", "n")
    sig = keep(sig)
    sets = set_table(docs, sig.select("id"))
    pairs = listed.where("id <> leader").select(F.col("leader").alias("a"), F.col("id").alias("b")).distinct()
    for k in ("a", "b"):
        pairs = pairs.join(sig.select(F.col("id").alias(k), F.col("sig").alias(f"sig_{k}")), k)
    pairs = pairs.where(F.size(F.array_intersect("sig_a", "sig_b")) >= match).select("a", "b")
    # a repeated id joins the classes of its texts
    of_class = rows.where("sig is not null").select("id", "print")
    again = of_class.groupBy("id").agg(F.min("print").alias("p"), F.max("print").alias("q")).where("p <> q").select("id")
    joined = keep(of_class.join(again, "id").join(classes.select("print", F.col("id").alias("class")), "print").select("id", "class"))
    least = joined.groupBy("id").agg(F.min("class").alias("a"))
    repeats = joined.join(least, "id").where("a <> class").select("a", F.col("class").alias("b"))
    linked = components(confirm(pairs, sets, percent).unionByName(repeats))

    home = keep(listed.groupBy("id").agg(F.max_by("leader", F.struct("lead", -F.col("leader"))).alias("home")))
    at = lambda done: keep(home.join(done, "id", "left").select("id", "home", F.coalesce("component", "id").alias("component")))
    placed = at(linked)
    sized = placed.join(sig, "id")
    open_homes = sized.groupBy("home").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.count("*").alias("n_all"), F.max("n").alias("most")).where("low <> high").select("home", "n_all", "most")
    lead = placed.select(F.col("id").alias("home"), F.col("component").alias("lead_component"))
    inside = sized.join(open_homes, "home").join(lead, "home").withColumn("minor", F.col("component") != F.col("lead_component"))
    minors = inside.where("minor").groupBy("home").agg(F.count("*").alias("n_minor"))
    found = keep(colliding(keep(inside.join(minors, "home").withColumn("key", F.col("home"))), "key", match, percent, across=False))
    linked = components(linked_in_blocks(found, sets, "key", percent), linked)

    placed = at(linked)
    spread = listed.select("key", "id", "leader").join(placed, "id").join(sig.select("id", "n"), "id")
    open_lists = spread.groupBy("key").agg(F.min("component").alias("c1"), F.max("component").alias("c2"), F.min("home").alias("h1"), F.max("home").alias("h2"), F.count("*").alias("n_all"), F.max("n").alias("most")).where("c1 <> c2 and h1 <> h2").select("key", "n_all", "most")
    lead = placed.select(F.col("id").alias("leader"), F.col("home").alias("lead_home"))
    inside = keep(spread.join(open_lists, "key").join(lead, "leader").withColumn("minor", F.col("home") != F.col("lead_home")))
    minors = inside.where("minor").groupBy("key").agg(F.count("*").alias("n_minor"))
    inside = inside.join(minors, "key").join(sig.select("id", "sig"), "id").join(prefix.select("id", "keys"), "id")
    found = keep(colliding(inside, "key", match, percent, across=True))
    linked = components(linked_in_blocks(found, sets, "key", percent), linked)

    named = classes.select("print", "id").join(linked, "id", "left").select("print", F.coalesce("component", "id").alias("class"))
    found = rows.select("id", "n_shingles", "print").join(keep(named), "print", "left")
    component = F.when(F.col("id").isNotNull(), F.coalesce("class", "id"))
    return found.select(F.col("id").alias(id_col), "n_shingles", component.alias("component_id"), F.coalesce(F.col("id") == component, F.lit(True)).alias("kept"))


def deduplicate(docs: DataFrame, id_col: str = "doc_id", **how) -> DataFrame:
    """docs with one document of each group, the one with the least id; all their columns."""
    gone = near_duplicates(docs, id_col, **how).where(~F.col("kept")).select(id_col)
    return docs.join(gone, id_col, "left_anti").select(docs.columns)
