"""Near-duplicate documents by MinHash with tensored banding, every link confirmed on full shingle sets.

A document's set holds its distinct runs of five words.  Documents with equal sets form a class; the rest
works on classes.  Two small collections of ``COLLECTION`` keys are computed, each key out of ``ROWS``
minhashes; the table keys are the pairs of a key of the first and one of the second collection, so
2 * 16 * 3 minhashes stand for 256 tables of six rows.  At similarity 0.75 a pair shares no table with a
probability of 3e-4, at 0.8 of 2e-5.  A pair key can only be shared if both of its parts are, so parts
are counted first and only classes whose parts recur form pair keys.

Buckets are linked by stars, not by all pairs: members are compared with one hub.  Where a bucket's
members are not all in one component after that, three other hubs are tried.  What is still split
then is decided in full: pairs across components in buckets of up to ``SMALL`` members, and larger buckets
block against block, where only documents outside the commonest component are looked up and only links
leave a task.  Links are confirmed on full sets, a hub's rows being salted.

Defined cases: null and empty texts have an empty set and link with nothing; a text of fewer than five
words is one shingle; rows with a null id take part, and their component is the least id among its
members that have one; repeated ids are separate rows of the same id; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import components
from .store import worker_cache, written
from .text import WordHashes, as_bytes, multipliers, pieces, shingle_set, space_words, unused

SHINGLE = 5
COLLECTION = 16
ROWS = 3
SEED = 20
ALIKE = (75, 100)
SALTS = 8
SMALL = 32
HUB_KEYS = 8
BLOCK = 1024


def word_hashes() -> WordHashes:
    return worker_cache().setdefault("words", WordHashes())


def minhash_keys(sets: list[np.ndarray], collection: int = COLLECTION, rows: int = ROWS, seed: int = SEED) -> np.ndarray:
    """Keys (sets x 2 * collection) of both collections; all sets are non-empty."""
    factors = multipliers(2 * collection * rows, seed)
    flat = np.concatenate(sets)
    starts = np.cumsum([0, *map(len, sets[:-1])])
    out = np.zeros((len(sets), 2 * collection), np.uint64)
    for i, f in enumerate(factors):
        slot = i // rows
        least = np.minimum.reduceat(flat * f, starts)
        out[:, slot] = (out[:, slot] ^ (least >> np.uint64(7))) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(slot + 1)
        out[:, slot] ^= out[:, slot] >> np.uint64(29)
    return out


def _fingerprint(s: np.ndarray) -> bytes:
    import xxhash

    return xxhash.xxh3_128_digest(s.tobytes())


def signatures(docs: DataFrame, text: str = "text", shingle: int = SHINGLE, number: str | None = None) -> DataFrame:
    """(rid, doc_id, n, print, keys): a number of its own (that in column ``number`` if given), the set's size and fingerprint, and the keys of each row."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, rid = word_hashes(), TaskContext.get().partitionId() << 40
        for batch in batches:
            for piece in pieces(batch, text, 1 << 18):
                sets = [shingle_set(hashes.of(space_words(t)), shingle) for t in as_bytes(piece.column(text))]
                full = [s for s in sets if len(s)]
                keys = minhash_keys(full).view(np.int64) if full else np.zeros((0, 0), np.int64)
                of = iter(keys)
                yield pa.RecordBatch.from_arrays(
                    [
                        piece.column(number) if number else pa.array(np.arange(rid, rid + len(sets)), pa.int64()),
                        piece.column("doc_id"),
                        pa.array([len(s) for s in sets], pa.int64()),
                        pa.array([_fingerprint(s) if len(s) else None for s in sets], pa.binary()),
                        pa.array([next(of) if len(s) else None for s in sets], pa.list_(pa.int64())),
                    ],
                    ["rid", "doc_id", "n", "print", "keys"],
                )
                rid += len(sets)

    kind = docs.schema["doc_id"].dataType.simpleString()
    return written(docs.select("doc_id", text, *([number] if number else [])).mapInArrow(sign, f"rid bigint, doc_id {kind}, n bigint, print binary, keys array<bigint>"), "signatures")


def buckets(classes: DataFrame, collection: int = COLLECTION) -> DataFrame:
    """(key, rid): members of every table bucket with more than one class, each set of members once."""
    parts = classes.select("rid", F.posexplode("keys").alias("slot", "part"))
    shared = parts.groupBy("part").count().where("count > 1").select("part")
    masks = parts.join(shared, "part", "left_semi").groupBy("rid").agg(F.bit_or(F.expr("shiftleft(1L, slot)")).alias("mask"))
    masks = masks.where(f"mask & {(1 << collection) - 1} <> 0 and mask >> {collection} <> 0")
    bit = lambda at: f"(mask >> ({at})) & 1 = 1"
    pairs = f"filter(sequence(0, {collection * collection - 1}), p -> {bit(f'p div {collection}')} and {bit(f'{collection} + p % {collection}')})"
    members = classes.join(masks, "rid").select("rid", "keys", F.explode(F.expr(pairs)).alias("p"))
    members = written(members.select(F.expr(f"xxhash64(p, keys[int(p div {collection})], keys[{collection} + p % {collection}])").alias("key"), "rid"), "bucket-members")
    stats = members.groupBy("key").agg(F.count("*").alias("c"), F.min("rid").alias("lo"), F.max("rid").alias("hi"), F.bit_xor(F.xxhash64("rid")).alias("x")).where("c > 1")
    once = stats.groupBy("c", "lo", "hi", "x").agg(F.min("key").alias("key"))
    return members.join(once.select("key", "c", "lo"), "key")


def full_sets(docs: DataFrame, wanted: DataFrame, text: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """(rid, shingles): the full sets of the classes in ``wanted`` (rid, doc_id, print), sorted 64-bit hashes as bytes."""
    want = wanted.select("rid", F.col("doc_id").alias("_id"), "print").hint("shuffle_hash")
    found = docs.select("doc_id", text).join(want, F.col("doc_id").eqNullSafe(F.col("_id"))).select("rid", "print", text)

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = word_hashes()
        for batch in batches:
            for piece in pieces(batch, text):
                rows = []
                for rid, known, body in zip(piece.column("rid").to_pylist(), piece.column("print").to_pylist(), as_bytes(piece.column(text)), strict=True):
                    s = shingle_set(hashes.of(space_words(body)), shingle)
                    if _fingerprint(s) == known:
                        rows.append((rid, s.tobytes()))
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.binary())], ["rid", "shingles"])

    return written(found.mapInArrow(build, "rid bigint, shingles binary"), "shingle-sets")


def confirm(pairs: DataFrame, sets: DataFrame, alike: tuple[int, int] = ALIKE) -> DataFrame:
    """(u, v, linked) of the pairs (hub u, member v), decided on full sets."""
    salted = sets.select(F.col("rid").alias("v"), F.col("shingles").alias("b")).join(pairs.select("u", "v"), "v").withColumn("salt", F.pmod(F.xxhash64("v"), F.lit(SALTS)))
    hubs = pairs.select("u", F.pmod(F.xxhash64("v"), F.lit(SALTS)).alias("salt")).distinct().join(sets.select(F.col("rid").alias("u"), F.col("shingles").alias("a")), "u")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            linked = []
            for a, b in zip(batch.column("a"), batch.column("b"), strict=True):
                a, b = np.frombuffer(a.as_buffer(), np.uint64), np.frombuffer(b.as_buffer(), np.uint64)
                small, large = (a, b) if len(a) < len(b) else (b, a)
                if len(small) * alike[1] < len(large) * alike[0]:
                    linked.append(False)
                    continue
                place = np.minimum(np.searchsorted(large, small), len(large) - 1)
                common = int((large[place] == small).sum())
                linked.append(common * alike[1] >= (len(a) + len(b) - common) * alike[0])
            yield pa.RecordBatch.from_arrays([batch.column("u"), batch.column("v"), pa.array(linked, pa.bool_())], ["u", "v", "linked"])

    return written(salted.join(hubs, ["u", "salt"]).select("u", "v", "a", "b").mapInArrow(compare, "u bigint, v bigint, linked boolean"), "confirmed")


def _split(members: DataFrame, roots: DataFrame) -> DataFrame:
    """Members (key, rid, root) of those buckets that hold more than one component."""
    now = members.join(roots, members["rid"] == roots["node"], "left").select("key", "rid", F.coalesce("root", "rid").alias("root"))
    mixed = now.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi").select("key")
    return written(now.join(mixed, "key", "left_semi"), "split-buckets")


def links(docs: DataFrame, signed: DataFrame, alike: tuple[int, int] = ALIKE) -> DataFrame:
    """(node, root) of all classes that are linked with another."""
    classes = written(signed.where("n > 0").groupBy("print").agg(F.min("rid").alias("rid"), F.first("keys").alias("keys"), F.min_by("doc_id", "rid").alias("doc_id")), "classes")
    members = written(buckets(classes), "buckets")
    stars = members.where("rid <> lo").select(F.col("lo").alias("u"), F.col("rid").alias("v")).distinct()
    involved = members.select("rid").distinct()
    sets = full_sets(docs, classes.join(involved, "rid", "left_semi"))
    done = confirm(stars, sets, alike)
    roots = components(done.where("linked").select("u", "v"))
    large = members.where(F.col("c") > SMALL)
    small = members.where((F.col("c") > 2) & (F.col("c") <= SMALL)).select("key", "rid")
    sample = large.where(F.pmod(F.xxhash64("key"), F.lit(HUB_KEYS)) == 0).select("key", "rid")
    members = _split(small.unionAll(sample), roots)
    hubs = members.groupBy("key").agg(F.array(*[F.min_by(F.struct("rid", "root"), F.xxhash64("rid", F.lit(turn))) for turn in (1, 2, 3)]).alias("hubs"))
    pairs = members.join(hubs, "key").select("rid", "root", F.explode("hubs").alias("h")).where("root <> h.root").select(F.col("h.rid").alias("u"), F.col("rid").alias("v")).distinct()
    known = done.select("u", "v").unionAll(done.select(F.col("v").alias("u"), F.col("u").alias("v")))
    done = written(done.unionAll(confirm(written(pairs.join(known, ["u", "v"], "left_anti"), "more-pairs"), sets, alike)), "confirmed-so-far")
    roots = components(done.where("linked").select("u", "v"))
    small = _split(small, roots)
    pairs = small.join(small.select("key", F.col("rid").alias("v"), F.col("root").alias("other")), "key").where("root < other").select(F.col("rid").alias("u"), "v").distinct()
    known = done.select("u", "v").unionAll(done.select(F.col("v").alias("u"), F.col("u").alias("v")))
    done = done.unionAll(confirm(written(pairs.join(known, ["u", "v"], "left_anti"), "more-pairs"), sets, alike))
    if not large.isEmpty():
        done = done.unionAll(block_links(large.select("lo", "rid").distinct(), roots, sets, alike))
    return components(done.where("linked").select("u", "v"))


def _overlaps(x: np.ndarray, keys: np.ndarray, owners: np.ndarray, n: int) -> np.ndarray:
    """How many shingles of ``x`` each of ``n`` owners has; ``keys`` are their shingles, sorted."""
    lo, hi = np.searchsorted(keys, x, "left"), np.searchsorted(keys, x, "right")
    count = hi - lo
    at = np.repeat(lo - np.cumsum(count) + count, count) + np.arange(int(count.sum()))
    return np.bincount(owners[at], minlength=n)


def _linked_in(a: list[tuple], b: list[tuple], same: bool, alike: tuple[int, int]) -> list[tuple[int, int]]:
    """Links across components between two blocks of (rid, root, set); at most one for a document and component.

    Only documents outside the blocks' commonest component are looked up: one end of a link across components always is.
    """
    roots, counts = np.unique([r for _, r, _ in a + b], return_counts=True)
    common = roots[counts.argmax()]
    out = []
    for left, right in ((a, b),) if same else ((a, b), (b, a)):
        flat = np.concatenate([s for _, _, s in right])
        owners = np.repeat(np.arange(len(right)), [len(s) for _, _, s in right])
        order = np.argsort(flat, kind="stable")
        keys, owners = flat[order], owners[order]
        sizes, root_of = np.array([len(s) for _, _, s in right]), np.array([r for _, r, _ in right])
        for rid, root, s in left:
            if root == common:
                continue
            shared = _overlaps(s, keys, owners, len(right))
            hit = np.flatnonzero((root_of != root) & (shared * alike[1] >= (sizes + len(s) - shared) * alike[0]))
            if len(hit):
                out += [(rid, right[i][0]) for i in hit[np.unique(root_of[hit], return_index=True)[1]].tolist()]
    return out


def block_links(edges: DataFrame, roots: DataFrame, sets: DataFrame, alike: tuple[int, int] = ALIKE) -> DataFrame:
    """(u, v, linked): links across components within large buckets, decided block against block.

    ``edges`` (lo, rid) tie the members of each bucket to its least.  Buckets that share members form a cluster;
    those of more than one component are dealt into blocks of about ``BLOCK`` documents.  A task sees
    two blocks at a time and emits links only, so neither pairs nor a cluster ever are rows of one task.
    """
    clusters = components(edges.select(F.col("lo").alias("u"), F.col("rid").alias("v")))
    docs = clusters.select(F.col("node").alias("rid"), F.col("root").alias("cluster")).join(roots, F.col("rid") == F.col("node"), "left").select("rid", "cluster", F.coalesce("root", "rid").alias("root"))
    split = docs.groupBy("cluster").agg(F.min("root").alias("a"), F.max("root").alias("b")).where("a < b").select("cluster")
    docs = written(docs.join(split, "cluster", "left_semi"), "clusters")
    sizes = docs.groupBy("cluster").agg(F.ceil(F.count(F.lit(1)) / F.lit(BLOCK)).alias("blocks"))
    dealt = docs.join(sizes, "cluster").withColumn("block", F.pmod(F.xxhash64("rid", F.lit(3)), F.col("blocks")))
    dealt = dealt.withColumn("with", F.explode(F.expr("sequence(0L, blocks - 1)")))
    dealt = dealt.select("cluster", F.least("block", "with").alias("i"), F.greatest("block", "with").alias("j"), (F.col("block") > F.col("with")).alias("second"), "rid", "root")
    dealt = dealt.join(sets.dropDuplicates(["rid"]), "rid").repartition("cluster", "i", "j").sortWithinPartitions("cluster", "i", "j")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, a, b = None, [], []

        def close() -> pa.RecordBatch:
            same = key is None or key[1] == key[2]
            found = _linked_in(a, a if same else b, same, alike) if a and (same or b) else []
            return pa.RecordBatch.from_arrays([pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64()), pa.array([True] * len(found), pa.bool_())], ["u", "v", "linked"])

        for batch in batches:
            for cluster, i, j, second, rid, root, body in zip(*(batch.column(c).to_pylist() for c in ("cluster", "i", "j", "second", "rid", "root", "shingles")), strict=True):
                if (cluster, i, j) != key:
                    if key is not None:
                        yield close()
                    key, a, b = (cluster, i, j), [], []
                (b if second else a).append((rid, root, np.frombuffer(body, np.uint64)))
        if key is not None:
            yield close()

    return written(dealt.mapInArrow(compare, "u bigint, v bigint, linked boolean"), "block-links")


def groups(docs: DataFrame, text: str = "text") -> DataFrame:
    """Per row: doc_id, n_shingles, component_id, kept."""
    signed = signatures(docs, text)
    roots = links(docs, signed)
    classes = signed.where("n > 0").groupBy("print").agg(F.min("rid").alias("rid"), F.min("doc_id").alias("least"))
    rooted = classes.join(roots, classes["rid"] == roots["node"], "left").select("print", "least", F.coalesce("root", "rid").alias("root"))
    named = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    by_print = rooted.join(named, "root").select("print", "component_id")
    out = signed.select("doc_id", "n", "print").join(by_print, "print", "left")
    out = out.withColumn("component_id", F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component_id")))
    return out.select("doc_id", F.col("n").alias("n_shingles"), "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def deduplicate(docs: DataFrame, text: str = "text") -> DataFrame:
    """One row of each group, with the columns of ``docs``: one with the least id (null only if none has an id).

    Rows are numbered, as ids may repeat or be null; equal rows are copies of one another, so one of them stays.  Rows
    without words are in no group and all stay.  Columns of any name pass.
    """
    row, kept_row = unused(docs.columns, "_row"), unused(docs.columns, "_kept")
    numbered = written(docs.withColumn(row, F.monotonically_increasing_id()), "numbered")
    signed = signatures(numbered, text, number=row)
    roots = links(numbered, signed)
    classes = signed.where("n > 0").groupBy("print").agg(F.min("rid").alias("rid"), F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", F.col("rid").alias("row"))).alias("first"))
    rooted = classes.join(roots, classes["rid"] == roots["node"], "left").select(F.coalesce("root", "rid").alias("root"), "first")
    kept = rooted.groupBy("root").agg(F.min("first").alias("first")).select(F.col("first.row").alias(kept_row))
    kept = kept.unionByName(signed.where("n = 0").select(F.col("rid").alias(kept_row))).hint("shuffle_hash")
    return numbered.join(kept, F.col(row) == F.col(kept_row), "left_semi").select(*docs.columns)
