"""Near-duplicate documents: SuperMinHash signatures, banding, verification, union-find grouping.

Words are ``[^\\x20\\x09-\\x0D]+`` after lower-casing A-Z; a document's set holds the
hashes of its distinct word shingles. SuperMinHash gives every element one random
permutation of the signature's slots: with the element's j-th draw, the value
j + r (0 <= r < 1) is put to the permutation's j-th slot, and a slot keeps its
smallest value. The draws of one level j are made for all elements of a slice of
documents at once, and a document is done as soon as all its slots hold values
below the next level: most documents stop after two or three levels.

Equal sets are grouped by a 128-bit digest of the whole set first, so copies cost nothing
afterwards; from there on a set goes by the digest's first half, not by a document's id.
Band keys that only one set has are left out by a count of keys alone and a bit table,
so a set's bands aren't shuffled. A bucket of the others is worked off without all its
pairs:

1. its smallest member is compared with all others;
2. links are turned into components; a bucket whose members are in one component is done;
3. a second member, outside the first one's component, is compared with all outside its own;
4. documents of buckets that still hold several components are compared exactly, by
   prefix filtering: with each set in one common order, rare elements first, two sets
   that are similar enough share an element among the first n - ceil(0.75 n) + 1 of
   each, at places that leave room for the overlap needed. Pairs of different
   components that do are compared.

So no pair that could join two components is left out, and big groups of near
copies cost one comparison a member. Every link is confirmed on the full sets.
With 32 bands of 4 slots a pair at similarity 0.75 shares no band with probability 5e-6.

Edge cases: null, empty and blank texts have an empty set and link with nothing;
texts with fewer words than a shingle are one element; long texts are taken whole;
ties go to the smallest doc_id; rows that share a doc_id are documents of their own,
linked by their texts only; a null doc_id is never the smallest, unless there is no
other; extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.llm.common import documents, fresh, materialise, slices
from tidelabel.llm.components import connected
from tidelabel.llm.hashbits import hash_bits, perhaps_in, surely_not_in

SHINGLE_WORDS = 5
SIMILARITY_PERCENT = 75
BANDS, BAND_SLOTS = 32, 4
#: Members of one comparison group; a larger one is split and its leader's set repeated.
GROUP_MEMBERS = 64
#: Slots of the counts that say which elements are rare; any order is right, a good one is fast.
RARITY_SLOTS = 1 << 20
WORD_CACHE = 500_000
GOLDEN = np.uint64(0x9E3779B97F4A7C15)
LOW = np.uint64(0xFFFFFFFF)
S32 = np.uint64(32)


def mixed(x: np.ndarray) -> np.ndarray:
    """The public splitmix64 finaliser."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Shingler:
    """Sorted distinct shingle hashes of texts."""

    def __init__(self, words: int = SHINGLE_WORDS):
        self.words, self.known = words, {}

    def hashes(self, text: str | None) -> np.ndarray:
        words = text.encode("utf-8").lower().split() if text else []
        if not words:
            return np.empty(0, dtype=np.uint64)
        known = self.known
        if len(known) > WORD_CACHE:
            known.clear()
        for w in set(words).difference(known):
            known[w] = xxhash.xxh3_64_intdigest(w)
        h = np.array([known[w] for w in words], dtype=np.uint64)
        n = len(h) - self.words + 1
        if n < 1:
            n, size = 1, len(h)
        else:
            size = self.words
        out = np.full(n, size, dtype=np.uint64)
        for i in range(size):
            out = mixed(out * GOLDEN + h[i : i + n])
        return np.unique(out)


def super_minhash(elements: np.ndarray, owner: np.ndarray, n_owners: int, slots: int) -> np.ndarray:
    """Signatures [n_owners, slots] of the sets whose elements and owners are given.

    A value is level << 32 | fraction. Owners without elements keep the largest value.
    """
    sig = np.full(n_owners * slots, np.iinfo(np.uint64).max, dtype=np.uint64)
    n = np.uint64(slots)
    z = mixed(elements + GOLDEN)
    k = (((z & LOW) * n) >> S32).astype(np.int64)
    np.minimum.at(sig, owner * slots + k, z >> S32)
    perm = None
    for level in range(1, slots):
        open_ = (sig.reshape(n_owners, slots).max(axis=1) >> S32) >= level
        keep = open_[owner]
        if not keep.any():
            break
        if perm is None:
            elements, owner, k = elements[keep], owner[keep], k[keep]
            perm = np.tile(np.arange(slots, dtype=np.uint16), (len(elements), 1))
            perm[np.arange(len(elements)), k] = 0
            perm[:, 0] = k
        elif not keep.all():
            elements, owner, perm = elements[keep], owner[keep], perm[keep]
        row = np.arange(len(elements))
        z = mixed(elements + np.uint64((int(GOLDEN) * (level + 1)) % (1 << 64)))
        k = level + (((z & LOW) * np.uint64(slots - level)) >> S32).astype(np.int64)
        slot = perm[row, k].astype(np.int64)
        perm[row, k] = perm[:, level]
        perm[:, level] = slot
        np.minimum.at(sig, owner * slots + slot, (np.uint64(level) << S32) | (z >> S32))
    return sig.reshape(n_owners, slots)


def signatures(sets: list[np.ndarray], slots: int, most: int = 60_000) -> np.ndarray:
    """SuperMinHash of many sets, worked off in groups of about ``most`` elements."""
    out, at = [], 0
    while at < len(sets):
        stop, size = at, 0
        while stop < len(sets) and (stop == at or size + len(sets[stop]) <= most):
            size += len(sets[stop])
            stop += 1
        part = sets[at:stop]
        owner = np.repeat(np.arange(len(part)), [len(x) for x in part])
        out.append(super_minhash(np.concatenate(part), owner, len(part), slots))
        at = stop
    return np.concatenate(out) if out else np.empty((0, slots), dtype=np.uint64)


def band_keys(sig: np.ndarray, bands: int, rows: int) -> np.ndarray:
    parts = sig.reshape(len(sig), bands, rows)
    key = np.broadcast_to(mixed(np.arange(1, bands + 1, dtype=np.uint64) * GOLDEN), (len(sig), bands)).copy()
    for i in range(rows):
        key = mixed(key * GOLDEN + parts[:, :, i])
    return key.astype(np.int64)


def sketch(docs: DataFrame, shingle: int = SHINGLE_WORDS, bands: int = BANDS, rows: int = BAND_SLOTS) -> DataFrame:
    """(doc_id, text_key, n_shingles, set_id, set_check, bands) of each document; the last three are null for empty sets.

    ``set_id`` and ``set_check`` are a digest of the whole set, ``text_key`` a hash of the text.
    """

    def run(batches):
        shingler = Shingler(shingle)
        for b in slices(batches):
            sets = [shingler.hashes(t) for t in b.column(2).to_pylist()]
            keys = band_keys(signatures(sets, bands * rows), bands, rows)
            empty = pa.array([len(s) == 0 for s in sets], pa.bool_())
            digest = np.frombuffer(b"".join(hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets), dtype=np.int64).reshape(-1, 2)
            halves = [pa.array(digest[:, i], mask=empty.to_numpy(zero_copy_only=False)) for i in (0, 1)]
            of = pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1, dtype=np.int32) * bands), pa.array(keys.ravel()), mask=empty)
            columns = [b.column(0), b.column(1), pa.array([len(s) for s in sets], pa.int64()), *halves, of]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "text_key", "n_shingles", "set_id", "set_check", "bands"])

    rows_in = docs.select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("text_key"), "text")
    return rows_in.mapInArrow(run, "doc_id long, text_key long, n_shingles long, set_id long, set_check long, bands array<long>")


def full_sets(texts: DataFrame, shingle: int) -> DataFrame:
    """(set_id, elements) from (set_id, text)."""

    def run(batches):
        shingler = Shingler(shingle)
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([shingler.hashes(t).tobytes() for t in b.column(1).to_pylist()], pa.binary())], names=["set_id", "elements"])

    return texts.select("set_id", "text").mapInArrow(run, "set_id long, elements binary")


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Those (a, b) of ``pairs`` whose full sets are similar enough.

    Members are sent to their leader ``a`` in groups of bounded size; a task reads a
    group's leader first and then streams its members.
    """
    sizes = pairs.groupBy("a").count()
    grouped = pairs.join(sizes, "a").selectExpr("a", "b", f"cast(pmod(xxhash64(b), ceil(count / {GROUP_MEMBERS})) as int) as part")
    leaders = grouped.select("a", "part").distinct().selectExpr("a", "part", "a as id", "0 as role")
    members = grouped.selectExpr("a", "part", "b as id", "1 as role")
    rows = leaders.union(members)
    named = perhaps_in(sets.withColumnRenamed("set_id", "id"), "id", hash_bits(rows, "id"))
    rows = rows.hint("merge").join(named, "id").select("a", "part", "role", "id", "elements")

    def run(batches):
        group, leader = None, None
        for b in slices(batches):
            kept: tuple[list, list] = ([], [])
            for a, part, role, i, raw in zip(*(b.column(c).to_pylist() for c in range(5))):
                s = np.frombuffer(raw, dtype=np.uint64)
                if (a, part) != group:
                    group, leader = (a, part), s
                if role:
                    common = len(np.intersect1d(leader, s, assume_unique=True))
                    if 100 * common >= percent * (len(leader) + len(s) - common):
                        kept[0].append(a)
                        kept[1].append(i)
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in kept], names=["a", "b"])

    return rows.repartition("a", "part").sortWithinPartitions("a", "part", "role").mapInArrow(run, "a long, b long")


def rarity(sets: DataFrame) -> np.ndarray:
    """Counts of elements over all sets, by slot; at most RARITY_SLOTS rows come to the driver."""

    def run(batches):
        n = np.zeros(RARITY_SLOTS, dtype=np.int64)
        for b in slices(batches):
            for raw in b.column(0).to_pylist():
                np.add.at(n, (np.frombuffer(raw, dtype=np.uint64) % np.uint64(RARITY_SLOTS)).astype(np.int64), 1)
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(n[at])], names=["slot", "n"])

    t = sets.select("elements").mapInArrow(run, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(RARITY_SLOTS, dtype=np.int64)
    out[t["slot"].to_numpy()] = t["n"].to_numpy()
    return out


def prefixes(sets: DataFrame, percent: int) -> DataFrame:
    """(set_id, element, place, n): each set's prefix in the order of rarity."""
    counts = sets.sparkSession.sparkContext.broadcast(rarity(sets))

    def run(batches):
        for b in slices(batches):
            ids, elements, places, sizes = [], [], [], []
            for i, raw in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                e = np.frombuffer(raw, dtype=np.uint64)
                n = len(e)
                order = np.lexsort((e, counts.value[(e % np.uint64(RARITY_SLOTS)).astype(np.int64)]))[: n + (-n * percent // 100) + 1]
                ids.append(np.full(len(order), i))
                elements.append(e[order].astype(np.int64))
                places.append(np.arange(len(order), dtype=np.int32))
                sizes.append(np.full(len(order), n))
            if ids:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (ids, elements, places, sizes)], names=["set_id", "element", "place", "n"])

    return sets.select("set_id", "elements").mapInArrow(run, "set_id long, element long, place int, n long")


def candidate_buckets(reps: DataFrame) -> DataFrame:
    """(key, set_id, n_shingles, rank, first): the members of all band keys that more than one set has.

    ``first`` is the member of smallest rank, that is of the smallest doc_id: often the text
    that the others were made from, and thus one leader for many buckets.
    """
    rank = F.struct("at.no_id", "at.doc_id", "set_id").alias("rank")
    keys = reps.select("set_id", "n_shingles", rank, F.explode("bands").alias("key"))
    # only keys are counted; the sets' ids go on where the key has another member
    shared = materialise(keys.groupBy("key").count().where("count > 1").select("key"), "minhash-shared-keys")
    met = perhaps_in(keys, "key", hash_bits(shared, "key"))
    firsts = met.groupBy("key").agg(F.count("*").alias("members"), F.min("rank").alias("r")).where("members > 1")
    return met.join(firsts.selectExpr("key", "members", "r.set_id as first"), "key")


def near_links(docs: DataFrame, reps: DataFrame, percent: int = SIMILARITY_PERCENT, shingle: int = SHINGLE_WORDS) -> DataFrame:
    """Links (a, b) between set_ids; reps: (set_id, at: (doc_id, text_key), n_shingles, bands) of each set."""
    buckets = materialise(candidate_buckets(reps), "minhash-buckets")
    members = buckets.select("set_id", "n_shingles").distinct()
    wanted = materialise(reps.select("set_id", "at.doc_id", "at.text_key").join(members.select("set_id"), "set_id", "left_semi").withColumn("spot", F.xxhash64("doc_id", "text_key")), "minhash-members")
    texts = docs.select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("text_key"), "text").withColumn("spot", F.xxhash64("doc_id", "text_key"))
    texts = perhaps_in(texts, "spot", hash_bits(wanted, "spot")).select("spot", "text")
    sets = materialise(full_sets(texts.join(wanted.select("spot", "set_id"), "spot").dropDuplicates(["spot"]), shingle), "minhash-full-sets")
    lengths = f"100 * least(n_a, n_b) >= {percent} * greatest(n_a, n_b)"

    def links_of(pairs: DataFrame) -> DataFrame:
        return materialise(confirmed(pairs, sets, percent), "minhash-links")

    of = lambda c: members.select(F.col("set_id").alias(c), F.col("n_shingles").alias(f"n_{c}"))
    tried = materialise(buckets.selectExpr("first as a", "set_id as b", "n_shingles as n_b").where("a <> b").distinct().join(of("a"), "a").where(lengths).select("a", "b"), "minhash-pairs")
    links = links_of(tried)

    def placed(rows: DataFrame) -> DataFrame:
        return rows.join(connected(links).withColumnRenamed("id", "set_id"), "set_id", "left").withColumn("component", F.coalesce("component", "set_id"))

    def undecided(rows: DataFrame, key: str) -> DataFrame:
        split = rows.groupBy(key).agg(F.min("component").alias("c"), F.max("component").alias("d")).where("c <> d").select(key)
        return materialise(rows.join(split, key, "left_semi"), "minhash-open")

    def more(pairs: DataFrame) -> DataFrame:
        return materialise(pairs.selectExpr("least(a, b) as a", "greatest(a, b) as b").distinct().join(tried, ["a", "b"], "left_anti"), "minhash-pairs")

    # the smallest member outside the first one's component leads next
    left = undecided(placed(buckets.where("members > 2").select("key", "set_id", "n_shingles", "rank", "first")), "key")
    if left.isEmpty():
        return links
    home = left.where("set_id = first").select("key", F.col("component").alias("home"))
    leader = left.join(home, "key").where("component <> home").groupBy("key").agg(F.min(F.struct("rank", "component", "n_shingles")).alias("x"))
    leader = leader.selectExpr("key", "x.rank.set_id as a", "x.component as c_a", "x.n_shingles as n_a")
    pairs = more(leader.join(left.selectExpr("key", "set_id as b", "component as c_b", "n_shingles as n_b"), "key").where("c_a <> c_b").where(lengths))
    links, tried = links.union(links_of(pairs)), tried.union(pairs)
    # what is still undecided is compared exactly
    left = undecided(placed(left.select("key", "set_id")), "key").select("set_id").distinct()
    if left.isEmpty():
        return links
    # a set that only seems to be open costs its prefix, but no shuffle of all sets
    open_sets = perhaps_in(sets, "set_id", hash_bits(left, "set_id"))
    rows = undecided(placed(materialise(prefixes(open_sets, percent), "minhash-prefixes")), "element")
    one, two = (rows.selectExpr("element", *(f"{c} as {c}_{x}" for c in ("set_id", "component", "place", "n"))) for x in "ab")
    room = f"{100 + percent} * least(n_a - place_a, n_b - place_b) >= {percent} * (n_a + n_b)"
    pairs = more(one.join(two, "element").where("set_id_a < set_id_b and component_a <> component_b").where(lengths).where(room).selectExpr("set_id_a as a", "set_id_b as b"))
    return links.union(links_of(pairs))


def near_groups(docs: DataFrame, percent: int = SIMILARITY_PERCENT, shingle: int = SHINGLE_WORDS, bands: int = BANDS, rows: int = BAND_SLOTS) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept, text_key), one row for each row of ``docs``."""
    sketches = materialise(sketch(docs, shingle, bands, rows), "minhash-sketches")
    at = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "text_key")
    reps = sketches.where("set_id is not null").groupBy("set_id", "set_check").agg(F.min(at).alias("at"), F.first("n_shingles").alias("n_shingles"), F.first("bands").alias("bands"))
    reps = materialise(reps, "minhash-sets")
    label = F.coalesce("component", "set_id").alias("label")
    labels = reps.select("set_id", "set_check", "at.doc_id").join(connected(near_links(docs, reps, percent, shingle)).withColumnRenamed("id", "set_id"), "set_id", "left").select("set_id", "set_check", "doc_id", label)
    labels = materialise(labels, "minhash-labels")
    least = labels.groupBy("label").agg(F.min("doc_id").alias("component_id"))
    of_set = labels.join(least, "label").select("set_id", "set_check", "component_id")
    own = F.coalesce("component_id", "doc_id")
    return sketches.select("doc_id", "text_key", "n_shingles", "set_id", "set_check").join(of_set, ["set_id", "set_check"], "left").select(
        "doc_id", "n_shingles", own.alias("component_id"), own.eqNullSafe(F.col("doc_id")).alias("kept"), "text_key"
    )


def one_of_each(docs: DataFrame, groups: DataFrame) -> DataFrame:
    """The rows of ``docs`` that ``near_groups`` keeps, and of kept rows that share id and group one.

    Rows are told by id and text; only the ids and hashes of rows that go, or that may be repeated, are joined.
    """
    spot, n = fresh(docs, "spot"), fresh(docs, "number")
    key = F.xxhash64("doc_id", "text_key").alias(spot)
    gone = materialise(groups.where("not kept").select(key).distinct(), "minhash-gone")
    several = groups.where("kept and n_shingles > 0").groupBy("doc_id", "component_id").agg(F.count("*").alias("rows"), F.collect_set("text_key").alias("texts")).where("rows > 1")
    repeated = materialise(several.select("doc_id", "component_id", F.explode("texts").alias("text_key")).select(key, F.xxhash64("doc_id", "component_id").alias(n)), "minhash-repeated")
    keyed = docs.withColumn(spot, F.xxhash64(F.col("doc_id").cast("long"), F.xxhash64("text")))
    kept = keyed.join(gone, spot, "left_anti")
    if repeated.isEmpty():
        return kept.select(*docs.columns)
    bits = hash_bits(repeated.select(F.col(spot).alias("k")), "k")
    perhaps = perhaps_in(kept, spot, bits).join(repeated, spot, "left")
    first = perhaps.where(F.col(n).isNotNull()).dropDuplicates([n])
    return surely_not_in(kept, spot, bits).select(*docs.columns).union(perhaps.where(F.col(n).isNull()).select(*docs.columns)).union(first.select(*docs.columns))


def op5_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_groups(documents(spark, sf_dir)).drop("text_key")
