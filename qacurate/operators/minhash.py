"""Near-duplicate questions by word-level MinHash and banding, with exact baselines.

Copies by normalised words collapse before any signature is made, so equal texts never meet in a
bucket. Text stays behind: signatures, bands and word hashes move, keyed by id.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from qacurate.functions.text import jaccard, md5_int, normalised, shingles
from qacurate.operators.graph import components
from qacurate.staging import Staged

PRIME = (1 << 31) - 1
SKETCH_BYTES = 32 << 20  # that go to each executor at once


def coefficients(num_perm: int = 128, seed: int = 7) -> list[tuple[int, int]]:
    """(a, b) of each permutation x -> (a x + b) mod PRIME, from md5, so that SQL can repeat them."""

    def draw(tag: str, i: int) -> int:
        return int(hashlib.md5(f"{seed}:{tag}:{i}".encode()).hexdigest()[:12], 16)

    return [(1 + draw("a", i) % (PRIME - 1), draw("b", i) % PRIME) for i in range(num_perm)]


def hashed(sets: Column | str) -> Column:
    """31-bit hashes of a set's members."""
    return F.transform(F.col(sets) if isinstance(sets, str) else sets, lambda w: md5_int(w).bitwiseAND(F.lit(PRIME)) % PRIME)


def exact_dedup(df: DataFrame, id_: str, text: str, scope: list[str] | None = None) -> DataFrame:
    """(id, keep): the smallest id with the same normalised words (and scope)."""
    keyed = df.select(F.col(id_).alias("id"), F.sha2(F.concat_ws("\x1f", *(scope or []), normalised(text)), 256).alias("key"))
    low = keyed.groupBy("key").agg(F.min("id").alias("keep"))
    return keyed.join(low, "key").select("id", "keep")


def minhash(df: DataFrame, sets: str = "set", num_perm: int = 128, seed: int = 7, drop: bool = False) -> DataFrame:
    """Adds ``signature``: the least value of each permutation over the set's hashes; null for an empty set.

    The hashes are made by column expressions; numpy permutes them batch by batch. drop: leaves the sets out.
    """
    pairs = np.array(coefficients(num_perm, seed), np.uint64)
    a, b, prime = pairs[:, :1], pairs[:, 1:], np.uint64(PRIME)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                column = part.column("_hashes")
                ends = np.cumsum(np.diff(column.offsets.to_numpy()))
                flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.uint64)
                low = np.full((part.num_rows, num_perm), PRIME, np.uint64)
                row = np.repeat(np.arange(part.num_rows), np.diff(ends, prepend=0))
                for k in range(0, len(flat), 1024):  # the matrix of one step is bounded, whatever the sets' sizes
                    mine = row[k : k + 1024]
                    starts = np.flatnonzero(np.diff(mine, prepend=-1))
                    value = a * flat[k : k + 1024] + b
                    for _ in range(2):  # 2^31 counts as 1; what is left is PRIME at most, which counts as 0
                        value = (value & prime) + (value >> np.uint64(31))
                    value[value == prime] = 0
                    least = np.minimum.reduceat(value, starts, axis=1).T
                    low[mine[starts]] = np.minimum(low[mine[starts]], least)
                filled = np.flatnonzero(np.diff(ends, prepend=0) > 0)
                sizes = np.zeros(part.num_rows + 1, np.int32)
                sizes[filled + 1] = num_perm
                values = pa.array(low[filled].ravel().astype(np.int64))
                lists = pa.ListArray.from_arrays(pa.array(np.cumsum(sizes, dtype=np.int32)), values, mask=pa.array(np.diff(ends, prepend=0) == 0))
                rest = part.drop_columns(["_hashes"])
                yield pa.RecordBatch.from_arrays([*rest.columns, lists], names=[*rest.schema.names, "signature"])

    hashes = df.withColumn("_hashes", F.coalesce(hashed(sets), F.array().cast("array<bigint>")))
    hashes = hashes.drop(sets) if drop else hashes
    schema = T.StructType([*[f for f in hashes.schema.fields if f.name != "_hashes"], T.StructField("signature", T.ArrayType(T.LongType()))])
    return hashes.mapInArrow(run, schema)


def lsh_bands(signed: DataFrame, bands: int = 32, rows: int = 4, scope: list[str] | None = None) -> DataFrame:
    """(id, band, key) for each band of a signature; scope columns keep bands of different scopes apart."""
    keys = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda i: F.md5(F.concat_ws(",", *[F.col(s) for s in scope or []], F.array_join(F.slice("signature", i * rows + 1, rows), ","))))
    return signed.where("signature is not null").select("id", F.posexplode(keys).alias("band", "key"))


def candidate_pairs(banded: DataFrame) -> DataFrame:
    """(a, b), a < b, that agree in some band. Ids only; buckets hold distinct texts."""
    x, y = banded.select(F.col("id").alias("a"), "band", "key"), banded.select(F.col("id").alias("b"), "band", "key")
    return x.join(y, ["band", "key"]).where("a < b").select("a", "b").distinct()


def sketches(sets: DataFrame) -> DataFrame:
    """(id, n, bits): size of ``hset`` and the parity of its members' counts by the low bits of their hashes, about 2 n bits.

    Each place where two parities differ takes a member that one of the sets lacks. Halves of a sketch, combined by
    exclusive or, are the sketch of half the width.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column("hset")
            n = np.diff(column.offsets.to_numpy())
            flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.uint64)
            ends = np.cumsum(n)
            bits = []
            for size_, end in zip(n.tolist(), ends.tolist(), strict=True):
                width = min(max(64, 1 << (2 * size_ - 1).bit_length()), 1 << 16) if size_ else 64
                places = np.bincount((flat[end - size_ : end] & np.uint64(width - 1)).astype(np.int64), minlength=width)
                bits.append(np.packbits((places & 1).astype(np.uint8), bitorder="little").tobytes())
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(n.astype(np.int32)), pa.array(bits, pa.binary())], names=["id", "n", "bits"])

    kept = sets.select("id", F.coalesce("hset", F.array().cast("array<bigint>")).alias("hset"))
    return kept.mapInArrow(run, T.StructType([kept.schema["id"], T.StructField("n", T.IntegerType()), T.StructField("bits", T.BinaryType())]))


def _may_reach(n: np.ndarray, bits: list[bytes], left: np.ndarray, right: np.ndarray | None, threshold: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places (i, j) of the pairs whose sizes and sketches allow the threshold; right None: pairs within left."""
    inner = right is None
    right = left if inner else right
    width = np.array([len(x) for x in bits])
    share = threshold / (1 + threshold)
    for w in np.unique(width):
        for x, y in ((left[width[left] == w], right[width[right] >= w]), (left[width[left] > w], right[width[right] == w])):
            if not len(x) or not len(y) or inner and width[x[0]] > w:  # inner: the first form has met these pairs
                continue
            p, q = (np.stack([_folded(bits[k], w) for k in z]) for z in (x, y))
            step = max(1, (1 << 20) // (len(y) * p.shape[1]))
            for at in range(0, len(x), step):
                i, j = x[at : at + step, None], y[None, :]
                both = n[i] + n[j]
                differ = np.bitwise_count(p[at : at + step, None, :] ^ q[None, :, :]).sum(axis=2, dtype=np.int64)
                fits = (np.minimum(n[i], n[j]) >= np.maximum(n[i], n[j]) * threshold - 1e-9) & ((both - differ) / 2 >= both * share - 1e-9)
                if inner:
                    fits &= (width[j] > w) | (i < j)
                a, b = np.nonzero(fits)
                yield x[at + a], y[b]


def _small_groups(g: np.ndarray, n: np.ndarray, bits: list[bytes], fresh: np.ndarray, threshold: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The same for pairs within many groups, whose rows lie together: all rows meet the next one of their group, then the one behind it ..."""
    width, share = np.array([len(x) for x in bits]), threshold / (1 + threshold)
    place, own, folds = np.zeros(len(g), np.int64), {}, {}
    for w in np.unique(width).tolist():
        rows = np.flatnonzero(width == w)
        place[rows] = np.arange(len(rows))
        own[w] = np.frombuffer(b"".join(bits[k] for k in rows), np.uint64).reshape(len(rows), w // 8)

    def folded(rows: np.ndarray, w: int, to: int) -> np.ndarray:
        if (w, to) not in folds:
            folds[w, to] = np.bitwise_xor.reduce(own[w].reshape(len(own[w]), -1, to // 8), axis=1)
        return folds[w, to][place[rows]]

    for d in range(1, len(g)):
        i = np.flatnonzero(g[:-d] == g[d:])
        if not len(i):
            return
        i = i[(fresh[i] | fresh[i + d]) & (np.minimum(n[i], n[i + d]) >= np.maximum(n[i], n[i + d]) * threshold - 1e-9)]
        for pair in np.unique(np.stack([width[i], width[i + d]], axis=1), axis=0).tolist():
            x = i[(width[i] == pair[0]) & (width[i + d] == pair[1])]
            differ = np.bitwise_count(folded(x, pair[0], min(pair)) ^ folded(x + d, pair[1], min(pair))).sum(axis=1, dtype=np.int64)
            both = n[x] + n[x + d]
            x = x[(both - differ) / 2 >= both * share - 1e-9]
            yield x, x + d


def _folded(bits: bytes, width: int) -> np.ndarray:
    return np.bitwise_xor.reduce(np.frombuffer(bits, np.uint64).reshape(-1, width // 8), axis=0)


def sketched_pairs(banded: DataFrame, sets: DataFrame | None, threshold: float, tile: int = 512, spent: list[Staged] | None = None, sketched: DataFrame | None = None) -> DataFrame:
    """(a, b): the candidate pairs that may reach the threshold by sizes and sketches; none that reaches it is lost.

    Rows meet in tiles of a bucket, so that a large bucket is dealt to many tasks; sets stay behind. Rows that
    ``banded`` marks as ``old`` do not meet each other, nor do those of one component ``c``. Where it has the number of rows of
    each bucket (``m``), it is taken as it is. sketched: the sketches of the sets, if they are written already. spent: gets the
    tables that the pairs are read from.
    """
    spent = [] if spent is None else spent

    def put(df: DataFrame, name: str) -> DataFrame:
        spent.append(Staged(df, name))
        return spent[-1].df

    old = F.col("old") if "old" in banded.columns else F.lit(False)
    part = [F.xxhash64("c").alias("c")] if "c" in banded.columns else []
    rows = banded.select("id", F.xxhash64("band", "key").alias("g"), old.alias("old"), *part, *(["m"] if "m" in banded.columns else []))
    met = rows
    if "m" not in banded.columns:
        rows = put(rows, "band-rows")
        sizes = rows.groupBy("g").agg(F.count(F.lit(1)).alias("m")).where("m > 1")
        met = put(rows.join(sizes, "g"), "bucket-rows")
    c = ["c"] if part else []
    if sketched is None:
        sketched = put(sketches(sets), "sketches")
    k = F.ceil(F.col("m") / tile)
    lone = met.where(F.col("m") <= tile).select("id", "g", "old", *c, F.lit(0).alias("side"))
    mine = met.where(F.col("m") > tile).withColumn("t", F.pmod(F.xxhash64("id"), k)).select("id", "g", "old", *c, "t", F.explode(F.sequence(F.lit(0).cast("long"), k - 1)).alias("u"))
    side = F.when(F.col("t") == F.col("u"), 0).when(F.col("t") < F.col("u"), 1).otherwise(2)
    dealt = mine.select("id", F.xxhash64("g", F.least("t", "u"), F.greatest("t", "u")).alias("g"), "old", *c, side.alias("side"))
    placed = lone.union(dealt).join(sketched, "id").repartition("g").sortWithinPartitions("g")

    def apart(rows: pa.Table, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not c or not len(i):
            return i, j
        of = rows.column("c").to_numpy()
        return i[of[i] != of[j]], j[of[i] != of[j]]

    def pairs(group: pa.Table) -> Iterator[pa.RecordBatch]:
        ids = group.column("id").combine_chunks()
        n, sides, bits = group.column("n").to_numpy().astype(np.int64), group.column("side").to_numpy(), group.column("bits").to_pylist()
        fresh = ~group.column("old").to_numpy()
        (lone, lone_old), (x1, o1), (x2, o2) = ((np.flatnonzero((sides == k) & fresh), np.flatnonzero((sides == k) & ~fresh)) for k in range(3))
        for x, y in ((lone, None), (lone, lone_old), (x1, x2), (x1, o2), (o1, x2)):
            if len(x) > (y is None) and (y is None or len(y)):
                for i, j in _may_reach(n, bits, x, y, threshold):
                    i, j = apart(group, i, j)
                    if len(i):
                        yield pa.RecordBatch.from_arrays([ids.take(pa.array(i)), ids.take(pa.array(j))], names=["a", "b"])

    def groups(rows: pa.Table) -> Iterator[pa.RecordBatch]:
        """Of whole groups: the many small ones at once, the others one by one."""
        g = rows.column("g").to_numpy()
        cuts = np.concatenate([[0], np.flatnonzero(np.diff(g)) + 1, [len(g)]])
        sizes = np.diff(cuts)
        whole = np.bincount(np.repeat(np.arange(len(sizes)), sizes), rows.column("side").to_numpy() > 0, len(sizes)) == 0
        for k in np.flatnonzero((sizes > 1) & ~((sizes <= 32) & whole)).tolist():
            yield from pairs(rows.slice(int(cuts[k]), int(sizes[k])))
        small = rows.filter(pa.array(np.repeat((sizes > 1) & (sizes <= 32) & whole, sizes)))
        if small.num_rows:
            ids, fresh = small.column("id").combine_chunks(), ~small.column("old").combine_chunks().to_numpy(zero_copy_only=False)
            for i, j in _small_groups(small.column("g").to_numpy(), small.column("n").to_numpy().astype(np.int64), small.column("bits").to_pylist(), fresh, threshold):
                i, j = apart(small, i, j)
                if len(i):
                    yield pa.RecordBatch.from_arrays([ids.take(pa.array(i)), ids.take(pa.array(j))], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch])
            g = batch.column("g").to_numpy()
            last = int(np.searchsorted(g, g[-1]))  # the last group may go on
            if last or (held and held[0].column("g")[0].as_py() != int(g[0])):
                yield from groups(pa.concat_tables([*held, table.slice(0, last)]))
                held = []
            held.append(table.slice(last))
        if held:
            yield from groups(pa.concat_tables(held))

    kind = sketched.schema["id"].dataType
    found = placed.mapInArrow(run, T.StructType([T.StructField("a", kind), T.StructField("b", kind)]))
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def may_reach(pairs: DataFrame, sketched: DataFrame, threshold: float) -> DataFrame:
    """(a, b): those of the pairs that sizes and sketches allow. Sketches move for it, a small part of what the sets take."""
    side = lambda x: sketched.select(F.col("id").alias(x), F.col("n").alias(f"n{x}"), F.col("bits").alias(f"s{x}"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            m = batch.num_rows
            if m:
                n, bits = np.empty(2 * m, np.int64), [b""] * (2 * m)
                for k, x in enumerate("ab"):
                    n[k::2], bits[k::2] = batch.column(f"n{x}").to_numpy(), batch.column(f"s{x}").to_pylist()
                found = [i for i, _ in _small_groups(np.repeat(np.arange(m), 2), n, bits, np.ones(2 * m, bool), threshold)]
                yield batch.select(["a", "b"]).take(pa.array(np.concatenate(found) // 2 if found else np.empty(0, np.int64)))

    met = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "na", "sa", "nb", "sb")
    return met.mapInArrow(run, T.StructType(met.schema.fields[:2]))


def linking_edges(banded: DataFrame, sets: DataFrame, threshold: float = 0.6, most: int = 64, spent: list[Staged] | None = None) -> DataFrame:
    """(a, b): verified pairs with the same connected components as all verified candidate pairs.

    Buckets of up to ``most`` rows give all their pairs. A larger one is settled in steps that are linear in
    its rows. Every row meets the bucket's most central one, that with the fewest members no other row has:
    two sets are alike only if both have few such members, so it links nearly all that can be linked. Rows
    outside the bucket's largest component then meet the most central of them. What is still apart goes
    through ``prefix_candidates``, which drops rows with too many members of their own at once. Tables go as soon as
    nothing reads them any more; spent: those that hold ``banded``, if it is written already.
    """
    if spent is None:
        spent = [Staged(banded, "bands")]
        banded = spent[0].df
    rows = banded
    sizes = Staged(rows.groupBy("band", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "buckets").df
    hset = F.col("hset") if "hset" in sets.columns else hash_set()
    small = sketched_pairs(rows.join(sizes.where(F.col("n") <= most), ["band", "key"], "left_semi"), sets.select("id", hset.alias("hset")), threshold, spent=spent)
    large = sizes.where(F.col("n") > most)
    if large.isEmpty():
        links = Staged(verify(small, sets, threshold).select("a", "b"), "links").df
        _drop(spent)
        return links
    held = Staged(rows.join(large, ["band", "key"], "left_semi"), "large-buckets").df
    coded = sets.select("id", hset.alias("hset")).join(held.select("id").distinct(), "id", "left_semi")
    spent.append(Staged(_own_members(coded), "own-members"))
    own = spent[-1].df
    placed = Staged(held.join(own.select("id", "own"), "id").select("band", "key", "id", "own"), "placed-rows").df
    first = Staged(verify(small.union(_stars(placed)).distinct(), sets, threshold).select("a", "b"), "first-links").df
    _drop(spent)
    apart = _apart(placed, first)
    if apart is None:
        return first
    second = Staged(verify(_stars(apart.where("minor")).distinct(), sets, threshold).select("a", "b"), "second-links").df
    both = first.union(second)
    apart = _apart(placed, both)
    if apart is None:
        return both
    open_ = Staged(coded.join(apart.groupBy("id").agg(F.max("c").alias("c"), F.max("minor").alias("minor")), "id"), "open-rows").df
    may = Staged(may_reach(prefix_candidates(open_, threshold, "c", "minor"), Staged(sketches(open_), "open-sketches").df, threshold), "open-pairs").df
    return both.union(verify(may, sets, threshold).select("a", "b"))


def linked(parts: Iterable[Staged], sets: DataFrame, threshold: float = 0.6, most: int = 64, wide: int = 1 << 14, dense: bool = False) -> DataFrame:
    """The edges of ``linking_edges`` with less on disk. Bands come in parts, each (id, band, key) of whole bands, which goes before
    the next one is made; what stays of it are pairs that sketches allow and rows of large buckets.

    Rows that are still apart after both rounds of central rows meet by sketches in buckets of up to ``wide`` rows, and by
    ``prefix_candidates`` in those above. Sketches rule pairs out before sets move, and sets move for pairs that are left
    only. dense: ids count up within a few ranges; see ``_only``.
    """
    coded = sets.select("id", (F.col("hset") if "hset" in sets.columns else hash_set()).alias("hset"))
    sketched = Staged(sketches(coded), "sketches")
    near, large = [], []
    for part in parts:
        several = Staged(part.df.groupBy("band", "key").agg(F.count(F.lit(1)).alias("m")).where("m > 1"), "buckets")
        met = Staged(part.df.join(several.df, ["band", "key"]), "bucket-rows")
        _drop([part, several])
        near.append(Staged(sketched_pairs(met.df.where(F.col("m") <= most), None, threshold, sketched=sketched.df), "near-pairs"))
        large.append(Staged(met.df.where(F.col("m") > most).select("band", "key", "id"), "large-buckets"))
        met.drop()
    pairs = reduce(DataFrame.union, [x.df for x in near])
    held = reduce(DataFrame.union, [x.df for x in large])
    check = lambda pairs: _verified(pairs, coded, sketched.df, threshold, dense)
    if held.isEmpty():
        links = check(pairs)
        _drop([*near, *large, sketched])
        return links
    own = _own_in_turns(_only(coded, held.select("id"), dense))
    placed = Staged(held.join(own.df, "id", "left").fillna(0, ["own"]).select("band", "key", "id", "own"), "placed-rows")
    _drop([*large, own])
    links = check(pairs.union(may_reach(_stars(placed.df).distinct(), sketched.df, threshold)))
    _drop(near)
    apart = _apart(placed.df, links)
    if apart is not None:
        links = links.union(check(may_reach(_stars(apart.where("minor")).distinct(), sketched.df, threshold)))
        apart = _apart(placed.df, links)
    if apart is not None:
        mid = Staged(apart.where(F.col("m") <= wide).select("band", "key", "id", "c", (~F.col("minor")).alias("old"), "m"), "apart-rows")
        last = sketched_pairs(mid.df, None, threshold, 2048, sketched=sketched.df)
        open_ = apart.where(F.col("m") > wide).groupBy("id").agg(F.max("c").alias("c"), F.max("minor").alias("minor"))
        if not open_.isEmpty():
            open_ = Staged(_only(coded, open_.select("id"), dense).join(open_, "id"), "open-rows").df
            last = last.union(may_reach(prefix_candidates(open_, threshold, "c", "minor"), sketched.df, threshold))
        links = links.union(check(last))
        mid.drop()
    _drop([placed, sketched])
    return links


def _drop(spent: list[Staged]) -> None:
    while spent:
        spent.pop().drop()


def _only(sets: DataFrame, ids: DataFrame, dense: bool) -> DataFrame:
    """The sets of the ids. dense: a bit for each id up to the largest of its range goes to every executor, and no set moves."""
    if not dense:
        return sets.join(ids.distinct(), "id", "left_semi")
    bits = Staged(ids.groupBy(F.bitmap_bucket_number("id").alias("g")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("id")).alias("bits")), "id-bits").df
    at = F.bitmap_bit_position("id")
    eight = F.conv(F.hex(F.substr("bits", (F.floor(at / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("long")
    met = sets.join(F.broadcast(bits), F.bitmap_bucket_number("id") == F.col("g"))
    return met.where(F.getbit(eight, (at % 8).cast("int")) == 1).select(sets.columns)


def _verified(pairs: DataFrame, coded: DataFrame, sketched: DataFrame, threshold: float, dense: bool) -> DataFrame:
    """(a, b) of the pairs at or above the threshold. dense: in turns, each of which moves about a quarter of the words of all sets at most."""
    held = Staged(pairs.distinct(), "pairs")
    if not dense:
        links = Staged(verify(held.df, coded, threshold).select("a", "b"), "links").df
        held.drop()
        return links
    words = sketched.agg(F.sum("n")).first()[0] or 0
    moved = held.df.join(sketched.select(F.col("id").alias("a"), "n"), "a").agg(F.sum("n")).first()[0] or 0
    turns = max(1, -(-4 * moved // max(words, 1)))
    links = []
    for turn in range(turns):
        mine = held.df.where(F.pmod(F.xxhash64("a", "b"), F.lit(turns)) == turn)
        sets = _only(coded, mine.select(F.col("a").alias("id")).union(mine.select("b")), dense)
        links.append(Staged(verify(mine, sets, threshold).select("a", "b"), "links").df)
    held.drop()
    return reduce(DataFrame.union, links)


def _own_in_turns(coded: DataFrame, turns: int = 4) -> Staged:
    """(id, own): how many members of each row no other row has; rows without any are left out. A part of the words moves at a time."""
    held, parts = Staged(coded, "held-sets"), []
    for turn in range(turns):
        each = held.df.select("id", F.explode(F.filter("hset", lambda w: F.pmod(w, F.lit(turns)) == turn)).alias("word"))
        alone = each.groupBy("word").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("df")).where("df = 1")
        parts.append(Staged(alone.groupBy("id").agg(F.count(F.lit(1)).alias("own")), "own-members"))
    held.drop()
    own = Staged(reduce(DataFrame.union, [x.df for x in parts]).groupBy("id").agg(F.sum("own").alias("own")), "own-members")
    _drop(parts)
    return own


def _own_members(coded: DataFrame) -> DataFrame:
    """(id, own): how many members of each row no other row has."""
    each = coded.select("id", F.explode("hset").alias("word"))
    alone = each.groupBy("word").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("df")).where("df = 1")
    return coded.select("id").join(alone.groupBy("id").agg(F.count(F.lit(1)).alias("own")), "id", "left").fillna(0, ["own"])


def _stars(placed: DataFrame) -> DataFrame:
    """(a, b): the rows of each bucket with its most central one."""
    centres = Staged(placed.groupBy("band", "key").agg(F.min(F.struct("own", "id")).alias("x")).select("band", "key", F.col("x.id").alias("centre")), "centres").df
    met = placed.join(centres, ["band", "key"]).where("id <> centre")
    return met.select(F.least("id", "centre").alias("a"), F.greatest("id", "centre").alias("b"))


def _apart(placed: DataFrame, links: DataFrame) -> DataFrame | None:
    """The rows of buckets that hold several components, with their component ``c``, whether it is a
    ``minor`` one of the bucket, and the bucket's number of rows ``m``; None if there are no such buckets."""
    named = placed.join(components(links), F.col("id") == F.col("node"), "left").select("band", "key", "id", "own", F.coalesce("component", "id").alias("c"))
    named = Staged(named, "named-rows").df
    parts = named.groupBy("band", "key", "c").agg(F.count(F.lit(1)).alias("m"))
    several = Staged(parts.groupBy("band", "key").agg(F.count(F.lit(1)).alias("k"), F.max_by("c", F.struct("m", "c")).alias("main"), F.sum("m").alias("m")).where("k > 1").select("band", "key", "main", "m"), "split-buckets").df
    return None if several.isEmpty() else named.join(several, ["band", "key"]).withColumn("minor", F.col("c") != F.col("main"))


def verify(pairs: DataFrame, sets: DataFrame, threshold: float = 0.6, mode: str = "exact") -> DataFrame:
    """(a, b, similarity) of the pairs at or above the threshold; sets: (id, set, signature).

    exact: Jaccard of the sets, whose members move as 64-bit hashes. estimate: share of equal signature entries.
    """
    what = F.col("signature") if mode != "exact" else F.col("hset") if "hset" in sets.columns else hash_set()
    left, right = sets.select(F.col("id").alias("a"), what.alias("sa")), sets.select(F.col("id").alias("b"), what.alias("sb"))
    met = pairs.join(left, "a").join(right, "b")
    if mode == "exact":
        sized = met.select("a", "b", F.size(F.array_intersect("sa", "sb")).cast("double").alias("n"), (F.size("sa") + F.size("sb")).alias("both"))
        return sized.select("a", "b", F.try_divide(F.col("n"), F.col("both") - F.col("n")).alias("similarity")).where(F.col("similarity") >= threshold)
    value = F.aggregate(F.zip_with("sa", "sb", lambda x, y: (x == y).cast("double")), F.lit(0.0), lambda s, x: s + x) / F.size("sa")
    return met.select("a", "b", value.alias("similarity")).where(F.col("similarity") >= threshold)


def hash_set() -> Column:
    """The members of ``set`` as 64-bit hashes: small to move and quick to intersect."""
    return F.transform("set", lambda w: F.xxhash64(w))


def solve_bands(threshold: float = 0.6, num_perm: int = 128, fp_weight: float = 0.5, fn_weight: float = 0.5) -> tuple[int, int]:
    """The (bands, rows) with the least weighted area of false positives below and false negatives above."""
    grid = np.linspace(0, 1, 401)
    best = (math.inf, 1, 1)
    for bands in range(1, num_perm + 1):
        for rows in range(1, num_perm // bands + 1):
            p = 1 - (1 - grid**rows) ** bands
            wrong = fp_weight * np.where(grid < threshold, p, 0).mean() + fn_weight * np.where(grid >= threshold, 1 - p, 0).mean()
            best = min(best, (float(wrong), bands, rows))
    return best[1], best[2]


def candidate_probability(similarity: float, bands: int = 32, rows: int = 4) -> float:
    return 1 - (1 - similarity**rows) ** bands


def prepared(df: DataFrame, id_: str, text: str, n: int = 1, scope: list[str] | None = None) -> tuple[DataFrame, DataFrame]:
    """(copies, sets): what exact copies keep, and a staged (id, scope..., set, signature) of those kept."""
    copies = Staged(exact_dedup(df, id_, text, scope), "exact").df
    kept = df.select(F.col(id_).alias("id"), *(scope or []), shingles(text, n).alias("set")).join(copies.where("id = keep").select("id"), "id", "left_semi")
    # The words themselves stay behind: 31-bit hashes make the signature, 64-bit hashes the exact check.
    coded = kept.select("id", *(scope or []), F.col("set").alias("_set"), hash_set().alias("hset"))
    return copies, Staged(minhash(coded, "_set", drop=True), "signatures").df


def similar_edges(df: DataFrame, id_: str, text: str, threshold: float = 0.6, n: int = 1, bands: int = 32, rows: int = 4, scope: list[str] | None = None) -> tuple[DataFrame, DataFrame]:
    """(copies, edges): edges (a, b, similarity) between texts that differ."""
    copies, sets = prepared(df, id_, text, n, scope)
    found = verify(sketched_pairs(lsh_bands(sets, bands, rows, scope), sets, threshold), sets, threshold)
    return copies, Staged(found, "similar").df


def minhash_dedup(df: DataFrame, id_: str, text: str, threshold: float = 0.6, keep: str = "components", prefer: Column | None = None, most: int = 64, **shape) -> DataFrame:
    """(id, keep_id): the row that stands for each row; id = keep_id are kept.

    keep: components (the smallest id of a connected component, or the largest ``prefer``), first (a row
    goes if a smaller id is similar), greedy (only if a smaller id that is itself kept is similar). The
    first form never pairs a large group with itself (see linking_edges); the others need all edges.
    """
    if keep == "components":
        copies, sets = prepared(df, id_, text, shape.get("n", 1), shape.get("scope"))
        banded = lsh_bands(sets, shape.get("bands", 32), shape.get("rows", 4), shape.get("scope"))
        named = components(linking_edges(banded, sets, threshold, most))
        found = copies.join(named, F.col("keep") == F.col("node"), "left").select("id", F.coalesce("component", "keep").alias("keep_id"))
        if prefer is None:
            return found
        ranked = found.join(df.select(F.col(id_).alias("id"), prefer.alias("rank")), "id")
        best = ranked.groupBy("keep_id").agg(F.max_by("id", F.struct("rank", -F.col("id"))).alias("best"))
        return ranked.join(best, "keep_id").select("id", F.col("best").alias("keep_id"))
    copies, edges = similar_edges(df, id_, text, threshold, **shape)
    gone = edges.groupBy(F.col("b").alias("keep")).agg(F.min("a").alias("by")) if keep == "first" else greedy_cover(edges)
    return copies.join(gone, "keep", "left").select("id", F.coalesce("by", "keep").alias("keep_id"))


def greedy_cover(edges: DataFrame) -> DataFrame:
    """(keep, by): rows dropped because a smaller kept id is similar, as an index filled in order of id would do.

    A round keeps the rows without a smaller open neighbour and drops their neighbours. The smallest open
    row is always settled, so the rounds end; they are as many as the longest chain of decisions.
    """
    spark = edges.sparkSession
    now = Staged(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct(), "greedy-open")
    dropped: list[DataFrame] = []
    while not (open_ := now.df).isEmpty():
        heads = open_.select(F.col("a").alias("id")).join(open_.select(F.col("b").alias("id")), "id", "left_anti").distinct()
        hit = Staged(open_.join(heads, open_.a == heads.id).groupBy(F.col("b").alias("keep")).agg(F.min("a").alias("by")), "greedy-hit").df
        dropped.append(hit)
        settled = hit.select(F.col("keep").alias("id")).union(heads)
        left = Staged(open_.join(settled, open_.a == settled.id, "left_anti").join(settled, F.col("b") == settled.id, "left_anti"), "greedy-open")
        now.drop()
        now = left
        if len(dropped) == 32:  # a long chain keeps its plan short
            dropped = [Staged(reduce(DataFrame.union, dropped), "greedy-dropped").df]
    return reduce(DataFrame.union, dropped) if dropped else spark.createDataFrame([], edges.select(F.col("b").alias("keep"), F.col("a").alias("by")).schema)


def prefix_candidates(rows: DataFrame, threshold: float, apart: str | None = None, minor: str | None = None) -> DataFrame:
    """(a, b), a < b: every pair that may reach the threshold; rows: (id, hset).

    Members are ranked from rare to common. Two sets that similar share a member among the first
    n - ceil(t n) + 1 of each, and their sizes differ by a factor of 1 / t at most. So a set meets only sets
    of its own size class and of the next one (classes grow by 1 / t), by member and class. Members that one
    row alone has come first and meet nothing; a row of too many has no other member in its prefix. What both
    prefixes share, and how much lies behind the last member they share, bounds the overlap of a pair; only
    pairs that may reach what they need are returned. apart: rows of one value of this column do not pair.
    minor: one row of a pair at least has this flag.
    """
    keys = [c for c in (apart, minor) if c]
    words = rows.select(*keys, "id", F.size("hset").alias("n"), F.explode("hset").alias("word"))
    ranks = words.groupBy("word").agg(F.count(F.lit(1)).alias("df"))
    ranked = words.join(ranks, "word").groupBy(*keys, "id", "n").agg(F.sort_array(F.collect_list(F.struct("df", "word"))).alias("w"))
    length = (F.col("n") - F.ceil(F.col("n") * threshold - 1e-9) + 1).cast("int")
    level = F.floor(F.log("n") / math.log(1 / threshold) + 1e-9).cast("int") if threshold < 1 else F.col("n")
    alone = F.size(F.filter("w", lambda x: x["df"] == 1))
    cut = ranked.select(*keys, "id", "n", level.alias("level"), alone.alias("own"), F.posexplode(F.slice("w", 1, length)).alias("pos", "x")).where("x.df > 1")
    prefix = Staged(cut.select(*keys, "id", "n", "level", "own", "pos", F.col("x.word").alias("word")), "prefixes").df

    def side(df: DataFrame, level_: Column, tag: str) -> DataFrame:
        named = [F.col(c).alias(f"{what}{tag}") for c, what in ((apart, "c"), (minor, "m")) if c]
        return df.select("word", level_.alias("level"), F.col("level").alias(f"l{tag}"), F.col("id").alias(tag), F.col("n").alias(f"n{tag}"), F.col("own").alias(f"o{tag}"), F.col("pos").alias(f"p{tag}"), *named)

    near = F.explode(F.array(F.col("level") - 1, F.col("level"), F.col("level") + 1))
    upper = F.explode(F.array(F.col("level") - 1, F.col("level")))
    once = (F.col("lb") > F.col("la")) | (F.col("a") < F.col("b"))
    if minor:  # rows of the flag on one side, all on the other
        x, y = side(prefix.where(F.col(minor)), F.col("level"), "a"), side(prefix, near, "b")
        once = (F.col("a") < F.col("b")) | ~F.col("mb")
    else:
        x, y = side(prefix, F.col("level"), "a"), side(prefix, upper, "b")
    needed = (F.col("na") + F.col("nb")) * (threshold / (1 + threshold)) - 1e-9
    behind = F.least(F.col("na") - F.col("pa"), F.col("nb") - F.col("pb"))
    fits = once & (F.least("na", "nb") >= F.greatest("na", "nb") * threshold - 1e-9)
    # Two sets of that overlap share a member among the first n - needed + 1 of each; and with any member they share,
    # what lies before and behind it in both must allow the overlap.
    fits = fits & (F.col("pa") <= F.col("na") - needed) & (F.col("pb") <= F.col("nb") - needed)
    fits = fits & (F.least(F.col("pa") - F.col("oa"), F.col("pb") - F.col("ob")) + behind >= needed)
    if apart:
        fits = fits & (F.col("ca") != F.col("cb"))
    met = x.join(y, ["word", "level"]).where(fits).groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"), F.max("pa").alias("pa"), F.max("pb").alias("pb"), F.first("na").alias("na"), F.first("nb").alias("nb"))
    may = met.where(F.col("shared") + behind - 1 >= needed)
    return may.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def scanned_pairs(sets: DataFrame, threshold: float) -> DataFrame:
    """(a, b), a < b: every pair that may reach the threshold by sizes and sketches; sets: (id, hset).

    Sketches, about 2 bits a member, go to every executor, ``SKETCH_BYTES`` of them at once in order of size; a row
    meets those of its own size up to 1 / threshold of it. No row is made for a pair that sketches rule out,
    however frequent a member is, and no bucket is formed. The comparisons grow with the square of the rows.
    """
    rows = Staged(sketches(sets).where("n > 0"), "sketches").df
    total = rows.agg(F.count(F.lit(1)), F.sum(F.length("bits") + 16)).first()
    chunks = max(1, -(-(total[1] or 0) // SKETCH_BYTES))
    dealt = rows.repartition(max(1, -(-total[0] // 4096)))
    found = [_met_sketches(rows.where(F.pmod(F.xxhash64("id"), F.lit(chunks)) == c) if chunks > 1 else rows, dealt, threshold) for c in range(chunks)]
    return reduce(DataFrame.union, found)


def _met_sketches(held: DataFrame, dealt: DataFrame, threshold: float) -> DataFrame:
    kind = dealt.schema["id"].dataType
    table = held.orderBy("n", "id").toArrow().combine_chunks()
    shared = dealt.sparkSession.sparkContext.broadcast(table.to_batches())
    slack = (1 - threshold) / (1 + threshold)  # of both sizes, at most, lies outside the overlap

    def folded(bits: pa.Array, width: int) -> np.ndarray:
        return np.ascontiguousarray(np.stack([_folded(x, width) for x in bits.to_pylist()]).T)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        large = pa.Table.from_batches(shared.value, table_schema)
        big, ids = large.column("n").to_numpy().astype(np.int64), large.column("id").combine_chunks()
        bits = large.column("bits").combine_chunks()
        widths, matrices = np.array([len(x) for x in bits.to_pylist()], np.int64), {}

        def of(width: int) -> tuple[int, np.ndarray]:
            """The first row as wide (rows are in order of size, and so of width), and the sketches from there on."""
            if width not in matrices:
                first = int(np.searchsorted(widths, width))
                matrices[width] = (first, folded(bits.slice(first), width) if first < len(widths) else np.empty((width // 8, 0), np.uint64))
            return matrices[width]

        for batch in batches:
            if not len(big) or not batch.num_rows:
                continue
            part = pa.Table.from_batches([batch]).sort_by([("n", "ascending")]).combine_chunks()
            n, mine, own = part.column("n").to_numpy().astype(np.int64), part.column("id").combine_chunks(), part.column("bits").combine_chunks()
            width = np.array([len(x) for x in own.to_pylist()], np.int64)
            cuts = [0, *(np.flatnonzero(np.diff(width)) + 1).tolist(), len(n)]
            for start, end in zip(cuts, cuts[1:], strict=False):
                w = int(width[start])
                first, q = of(w)
                for at in range(start, end, 64):
                    stop = min(at + 64, end)
                    p = folded(own.slice(at, stop - at), w)
                    low, high = np.searchsorted(big, n[at]), np.searchsorted(big, n[stop - 1] / threshold + 1e-6, side="right")
                    for j in range(max(int(low), first), int(high), 4096):
                        upto = min(j + 4096, int(high))
                        differ = np.zeros((stop - at, upto - j), np.uint16 if w < 8000 else np.uint32)
                        for k in range(w // 8):
                            differ += np.bitwise_count(p[k][:, None] ^ q[k, j - first : upto - first][None, :])
                        both = n[at:stop, None] + big[None, j:upto]
                        fits = (differ <= both * slack + 1e-6) & (n[at:stop, None] <= big[None, j:upto]) & (n[at:stop, None] >= big[None, j:upto] * threshold - 1e-6)
                        x, y = np.nonzero(fits)
                        if len(x):
                            yield pa.RecordBatch.from_arrays([mine.take(pa.array(x + at)), ids.take(pa.array(y + j)), pa.array((n[x + at] == big[y + j]).astype(bool))], names=["a", "b", "even"])

    table_schema = table.schema
    met = dealt.mapInArrow(run, T.StructType([T.StructField("a", kind), T.StructField("b", kind), T.StructField("even", T.BooleanType())]))
    # Rows of one size meet from both sides.
    return met.where((F.col("a") < F.col("b")) | ((F.col("a") > F.col("b")) & ~F.col("even"))).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def exact_similarity_join(sets: DataFrame, threshold: float = 0.6) -> DataFrame:
    """(a, b, similarity) of all pairs with a Jaccard of the threshold or more; sets: (id, set).

    Words count as their 64-bit hashes.
    """
    coded = Staged(sets.select("id", hash_set().alias("hset")), "coded-sets").df
    return verify(Staged(scanned_pairs(coded, threshold), "scanned-pairs").df, coded, threshold)


def jaccard_bruteforce(sets: DataFrame, threshold: float = 0.6, most: int = 3000) -> DataFrame:
    """The same by comparing every pair; refuses more than ``most`` rows. For tests."""
    if sets.limit(most + 1).count() > most:
        raise ValueError(f"brute force is for {most} rows at most")
    x, y = sets.select(F.col("id").alias("a"), F.col("set").alias("sa")), sets.select(F.col("id").alias("b"), F.col("set").alias("sb"))
    return x.join(y, F.col("a") < F.col("b")).select("a", "b", jaccard("sa", "sb").alias("similarity")).where(F.col("similarity") >= threshold)


def ml_minhash(sets: DataFrame, threshold: float = 0.6, tables: int = 64) -> DataFrame:
    """(a, b, similarity) by the ML library's features and MinHash: pairs with an equal hash in some table.

    The rows are those of the library's own join, which makes a row for each pair and table that agree, so for nearly
    all pairs of texts. Here pairs that can be near enough are found first, and the model's hashes are asked for those.
    """
    from pyspark.ml.feature import HashingTF, MinHashLSH

    vectors = HashingTF(inputCol="set", outputCol="features", numFeatures=1 << 18, binary=True).transform(sets.where(F.size("set") > 0))
    model = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=tables, seed=7).fit(vectors)
    stored = lambda c, kind: F.from_json(F.to_json(F.struct(F.col(c).alias("x"))), f"x {kind}")["x"]  # noqa: E731  what a vector holds
    hashed_ = model.transform(vectors.select("id", "features"))
    rows = hashed_.select("id", stored("features", "struct<indices: array<bigint>>")["indices"].alias("hset"), F.transform(stored("hashes", "array<struct<values: array<double>>>"), lambda h: h["values"][0].cast("long")).alias("signature"))
    coded = Staged(rows, "ml-features").df
    near = Staged(verify(scanned_pairs(coded, threshold), coded, threshold), "ml-near").df
    x, y = coded.select(F.col("id").alias("a"), F.col("signature").alias("sa")), coded.select(F.col("id").alias("b"), F.col("signature").alias("sb"))
    return near.join(x, "a").join(y, "b").where(F.exists(F.zip_with("sa", "sb", lambda p, q: p == q), lambda e: e)).select("a", "b", "similarity")


def dedup_quality(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Recall and precision of found pairs against true ones."""
    both = found.select("a", "b", F.lit(1).alias("f")).join(truth.select("a", "b", F.lit(1).alias("t")), ["a", "b"], "full")
    counts = both.agg(F.count("f").alias("n_found"), F.count("t").alias("n_true"), F.count_if(F.col("f").isNotNull() & F.col("t").isNotNull()).alias("n_both"))
    return counts.select("*", F.round(F.try_divide(F.col("n_both").cast("double"), F.col("n_true")), 6).alias("recall"), F.round(F.try_divide(F.col("n_both").cast("double"), F.col("n_found")), 6).alias("precision"))
