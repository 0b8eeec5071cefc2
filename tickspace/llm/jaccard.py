"""Exact set-similarity self-join of documents by shingles, for components.

Plan
----
1. One scan hashes every text's distinct shingles.  Texts with equal sets form
   one class (key of set hash and size); a sketch of fixed size counts how
   common shingles are.
2. Prefix filter: with similarity t, linked sets of sizes n share one of the
   first n - ceil(t n) + 1 shingles under ANY global order.  The first order
   puts rarer shingles (by the sketch) first, so passages that many texts share
   are hardly ever in a prefix.  Two further orders are hash orders; a pair's
   short prefixes must meet under both before its whole sets are fetched.
3. Star round: in each bucket (one prefix shingle) every class is compared only
   with the bucket's most central class: rows, not pairs.  That class is found by
   a pre-aggregated maximum and joined back, so a hot bucket is split.
4. Remaining round: pairs of one bucket whose classes the links so far have NOT
   put into one component; in large buckets, of the members near the bucket's
   head, only those that also share enough of their differences from the head (a
   group of near copies that are not quite similar enough would else be compared
   pair by pair).  Within a component no further comparison can change
   the result, so a group of thousands of near copies costs a row per copy, and
   no link between different components is lost.
5. Components over all links; every text gets its smallest reachable doc_id.

Any order is correct: the sketch's error changes only the speed.

Defined cases: null, empty or blank text: size 0, linked with nothing (its
component is its own id); repeated rows are equal sets, hence linked if not
empty; extra columns are ignored; an empty table gives an empty result; rows
whose id is null take part but never name a component unless alone (null).
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .shared import bounded, materialise, remove, shared_dir
from .textkernel import BLANKS, U, chunks, grams, mix, words

BUCKET = 1000  #: larger buckets are compared by differences from their head
SLOT_BITS = 18  #: the sketch has 2**SLOT_BITS counters, whatever the input
_PIECE = 1 << 12
_KEEP = U((1 << 56) - 1)


def _level(sketch: np.ndarray | None) -> np.ndarray | None:
    """How far each counter stands out of the noise, in powers of two."""
    if sketch is None:
        return None
    mean = sketch.mean()
    over = sketch - mean - 6 * np.sqrt(mean) - 8
    return np.where(over > 0, np.log2(np.maximum(over, 1)) + 1, 0).astype(np.uint8)


def doc_sets(column: pa.Array, k: int, level: np.ndarray | None) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, offsets, tokens): for each text its distinct shingle tokens,
    ascending, in tokens[offsets[i]:offsets[i+1]].  The top byte of a token is
    its shingle's level, the rest a 56-bit hash: ascending order is order one."""
    for row, end, data, off in chunks(column):
        n = end - row
        w = words(data, off, BLANKS)
        first = w.first(n)
        count = np.diff(first)
        g = grams(w.hash, k)
        text = w.text[: len(g)]
        full = text == w.text[k - 1 :] if len(g) else np.zeros(0, bool)
        g, text = g[full], text[full]
        small = np.flatnonzero((count > 0) & (count < k))
        if len(small):
            short = np.array([grams(w.hash[first[i] : first[i + 1]], int(count[i]))[0] for i in small], U)
            g, text = np.concatenate([g, short]), np.concatenate([text, small])
        token = mix(g, 1) & _KEEP
        if level is not None:
            token |= level[(token >> U(56 - SLOT_BITS)).astype(np.int64)].astype(U) << U(56)
        order = np.lexsort((token, text))
        token, text = token[order], text[order]
        if len(token):
            new = np.empty(len(token), bool)
            new[0] = True
            new[1:] = (token[1:] != token[:-1]) | (text[1:] != text[:-1])
            token, text = token[new], text[new]
        yield row, np.searchsorted(text, np.arange(n + 1)), token


def _keys(off: np.ndarray, token: np.ndarray) -> np.ndarray:
    """64-bit class keys of sets, without levels; 0 for empty sets."""
    size = np.diff(off)
    plain = token & _KEEP
    with np.errstate(over="ignore"):
        lanes = []
        for salt in (2, 3):
            total = np.zeros(len(plain) + 1, U)
            np.cumsum(mix(plain, salt), out=total[1:])
            lanes.append(total[off[1:]] - total[off[:-1]])
        key = mix(lanes[0] ^ mix(lanes[1] + size.astype(U), 4), 5)
    key[size == 0] = 0
    return key.view(np.int64)


def _prefix(size: np.ndarray, num: int, den: int) -> np.ndarray:
    return np.where(size > 0, size - (num * size + den - 1) // den + 1, 0)


def _odd(tokens: np.ndarray) -> bytes:
    """Parities of the set's hashes in as many slots as it has tokens, about."""
    m = max(64, 1 << int(len(tokens)).bit_length())
    return np.packbits((np.bincount((tokens & U(m - 1)).astype(np.int64), minlength=m) & 1).astype(bool), bitorder="little").tobytes()


def differing(a: bytes, b: bytes) -> int:
    """A lower bound of the number of tokens that only one of two sets has:
    slots of unlike parity, the larger sketch being folded onto the smaller."""
    x, y, m, n = int.from_bytes(a, "little"), int.from_bytes(b, "little"), len(a), len(b)
    if m < n:
        x, y, m, n = y, x, n, m
    while m > n:
        m //= 2
        x = (x >> 8 * m) ^ (x & ((1 << 8 * m) - 1))
    return (x ^ y).bit_count()


def _close(num: int, den: int, times: int = 1):
    """Pairs whose parity sketches differ in no more slots than ``times`` the
    number of shingles that linked sets may differ in."""

    def run(batches):
        for batch in batches:
            u, v = np.asarray(batch.column(0)), np.asarray(batch.column(1))
            ok = np.zeros(len(u), bool)
            for i, (n, a, m, b) in enumerate(zip(*(batch.column(j).to_pylist() for j in range(2, 6)))):
                ok[i] = differing(a, b) <= times * (n + m - 2 * (-(-num * (n + m) // (num + den))))
            yield pa.RecordBatch.from_arrays([pa.array(u[ok]), pa.array(v[ok])], ["u", "v"])

    return run


def _scan(k: int):
    def run(batches):
        sketch = np.zeros(1 << SLOT_BITS, np.int64)
        for batch in batches:
            ids, keys, sizes, odd = batch.column(0), [], [], []
            for _, off, token in doc_sets(batch.column(1), k, None):
                sketch += np.bincount((token >> U(56 - SLOT_BITS)).astype(np.int64), minlength=len(sketch))
                keys.append(_keys(off, token))
                sizes.append(np.diff(off))
                odd += [_odd(token[a:b]) if b > a else None for a, b in zip(off[:-1], off[1:])]
            n = len(ids)
            if n:
                yield pa.RecordBatch.from_arrays([ids, pa.array(np.concatenate(keys)), pa.array(np.concatenate(sizes).astype(np.int64)), pa.array(odd, pa.binary()), pa.nulls(n, pa.int32()), pa.nulls(n, pa.binary())], ["doc_id", "key", "n", "odd", "piece", "counts"])
        pieces = [zlib.compress(sketch[i : i + _PIECE].astype(np.uint32).tobytes(), 1) for i in range(0, len(sketch), _PIECE)] if sketch.any() else []
        if pieces:
            m = len(pieces)
            yield pa.RecordBatch.from_arrays([pa.nulls(m, pa.int64()), pa.nulls(m, pa.int64()), pa.nulls(m, pa.int64()), pa.nulls(m, pa.binary()), pa.array(range(m), pa.int32()), pa.array(pieces, pa.binary())], ["doc_id", "key", "n", "odd", "piece", "counts"])

    return run


def _add_counts(batches):
    """Sum of the counters of one piece, over one salted share of the tasks."""
    held: dict[int, np.ndarray] = {}
    for batch in batches:
        for piece, blob in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            x = np.frombuffer(zlib.decompress(blob), np.uint32).astype(np.uint64)
            held[piece] = held[piece] + x if piece in held else x
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([x.tobytes() for x in held.values()], pa.binary())], ["piece", "counts"])


def _sketch(scan: DataFrame) -> np.ndarray:
    parts = scan.where("piece is not null").select("piece", "counts").coalesce(64).mapInArrow(_add_counts, "piece int, counts binary")
    out = np.zeros(1 << SLOT_BITS, np.uint64)
    for piece, blob in parts.toLocalIterator():  # fixed size: 64 partial sketches at most
        out[piece * _PIECE : (piece + 1) * _PIECE] += np.frombuffer(bytes(blob), np.uint64)
    return out.astype(np.float64)


def _entries(k: int, num: int, den: int, level_b):
    def run(batches):
        level, seen = level_b.value, set()
        for batch in batches:
            for _, off, token in doc_sets(batch.column(0), k, level):
                key, size = _keys(off, token), np.diff(off)
                take = _prefix(size, num, den)
                for i, x in enumerate(key.tolist()):  # copies within a task once
                    if x in seen:
                        take[i] = 0
                    else:
                        seen.add(x)
                if len(seen) > 200_000:
                    seen.clear()
                if not take.sum():
                    continue
                common = np.zeros(len(token) + 1, np.int64)
                np.cumsum((token >> U(56)) > 0, out=common[1:])
                central = ((common[off[1:]] - common[off[:-1]]) * 1_000_000 // np.maximum(size, 1)).astype(np.int32)
                of = np.repeat(np.arange(len(size)), take)
                pos = np.arange(len(of)) - np.repeat(np.cumsum(take) - take, take)
                yield pa.RecordBatch.from_arrays([pa.array(token[off[of] + pos].view(np.int64)), pa.array(key[of]), pa.array(size[of].astype(np.int32)), pa.array(pos.astype(np.int32)), pa.array(central[of])], ["token", "key", "n", "pos", "central"])

    return run


def _full_sets(k: int, num: int, den: int, level_b):
    """Of wanted texts: key, whole set, prefixes under the two other orders."""

    def run(batches):
        level = level_b.value
        for batch in batches:
            want = np.asarray(batch.column(1))
            for row, off, token in doc_sets(batch.column(0), k, level):
                key, size = _keys(off, token), np.diff(off)
                take = _prefix(size, num, den)
                out = []
                for i in np.flatnonzero(key == want[row : row + len(key)]):
                    s = token[off[i] : off[i + 1]]
                    p = int(take[i])
                    others = [np.sort(s[np.argpartition(mix(s, salt), p - 1)[:p]]) if p < len(s) else s for salt in (7, 8)]
                    out.append((key[i], s.tobytes(), *(x.tobytes() for x in others)))
                if out:
                    cols = list(zip(*out))
                    yield pa.RecordBatch.from_arrays([pa.array(np.array(cols[0], np.int64)), *(pa.array(c, pa.binary()) for c in cols[1:])], ["key", "full", "p2", "p3"])

    return run


def _shared(a: bytes, b: bytes) -> int:
    return len(np.intersect1d(np.frombuffer(a, U), np.frombuffer(b, U), assume_unique=True))


def _pairs_that(test):
    """Pairs u, v of the first two columns whose further columns pass."""

    def run(batches):
        for batch in batches:
            u, v = np.asarray(batch.column(0)), np.asarray(batch.column(1))
            ok = np.fromiter((test(*x) for x in zip(*(c.to_pylist() for c in batch.columns[2:]))), bool, batch.num_rows)
            yield pa.RecordBatch.from_arrays([pa.array(u[ok]), pa.array(v[ok])], ["u", "v"])

    return run


def _meet(p2: bytes, p3: bytes, q2: bytes, q3: bytes) -> bool:
    """Do the prefixes under the second and the third order meet?"""
    return _shared(p2, q2) > 0 and _shared(p3, q3) > 0


def _similar(num: int, den: int):
    def test(a: bytes, b: bytes) -> bool:
        both = _shared(a, b)
        return den * both >= num * ((len(a) + len(b)) // 8 - both)

    return test


def _differences(num: int, den: int):
    return lambda batches: _differing_tokens(batches, num, den)


def _differing_tokens(batches, num: int, den: int):
    """The first tokens that only a class or only its bucket's head has, in
    order, as many as a link may differ in and one; one row without a token
    where there are none."""
    for batch in batches:
        c = [x.to_pylist() for x in batch.columns]
        tokens, sizes = [], []
        for n, full, head in zip(c[2], c[5], c[6]):
            t = np.setxor1d(np.frombuffer(full, U), np.frombuffer(head, U), assume_unique=True)
            sizes.append(len(t))
            tokens.append(t[: (n + n * den // num) * (den - num) // (den + num) + 1])
        rows = np.repeat(np.arange(batch.num_rows), [max(len(t), 1) for t in tokens])
        none = [None]
        yield pa.RecordBatch.from_arrays(
            [*(batch.column(i).take(pa.array(rows)) for i in range(5)), pa.array([x for t in tokens for x in (t.view(np.int64).tolist() if len(t) else none)], pa.int64()), pa.array(np.array(sizes, np.int32)[rows]), pa.array([i for t in tokens for i in range(max(len(t), 1))], pa.int32())],
            ["pivot", "key", "n", "root", "main", "token", "size", "pos"],
        )


class _Join:
    def __init__(self, docs: DataFrame, k: int, num: int, den: int):
        self.docs, self.k, self.num, self.den = bounded(docs), k, num, den
        self.spark = docs.sparkSession
        self.base = shared_dir(self.spark)
        scan = materialise(docs.select("doc_id", "text").mapInArrow(_scan(k), "doc_id bigint, key bigint, n bigint, odd binary, piece int, counts binary"), "scan", self.base)
        self.members = scan.where("piece is null").select("doc_id", "key", "n")
        self.odd = scan.where("piece is null and n > 0").select("key", "n", "odd")
        self.level = self.spark.sparkContext.broadcast(_level(_sketch(scan)))

    def possible(self, a: str, b: str):
        """Size and position filters of two entries of one bucket, as if the
        bucket's were their first shared shingle: a linked pair passes there."""
        n, m, i, j = (F.col(f"{x}.{y}").cast("bigint") for y in ("n", "pos") for x in (a, b))
        need = F.ceil((n + m) * self.num / F.lit(float(self.num + self.den)) - 1e-9)
        return (F.least(n, m) * self.den >= F.greatest(n, m) * self.num) & (F.least(n - i, m - j) >= need)

    def sets(self, keys: DataFrame, name: str) -> DataFrame:
        """Whole sets and further prefixes of the classes in column ``key``."""
        # written, so that its true size decides on how the texts are joined
        one = materialise(self.members.join(keys, "key").groupBy("key").agg(F.min("doc_id").alias("doc_id")).select("doc_id", "key").coalesce(8), f"{name}_texts", self.base)
        found = self.docs.select("doc_id", "text").join(one, self.docs["doc_id"].eqNullSafe(one["doc_id"])).select("text", "key")
        return materialise(found.mapInArrow(_full_sets(self.k, self.num, self.den, self.level), "key bigint, full binary, p2 binary, p3 binary").dropDuplicates(["key"]), f"{name}_sets", self.base)

    def deviating(self, rows: DataFrame) -> DataFrame:
        """Candidate pairs of large buckets, by how members differ from the
        bucket's head h (members that are near it): x and y differ in at least |x^h| + |y^h| - 2 shared
        differences, so a pair that differs in at most d shingles shares
        ceil((|x^h| + |y^h| - d) / 2) of these differences, rare ones first.
        If that is none, one of the two is all but equal to the head, and the
        smallest class of its size and kind stands for the others like it."""
        members = materialise(rows.select("pivot", F.col("a.key").alias("key"), F.col("a.n").alias("n"), "root", "main").distinct(), "dev_members", self.base)
        if members.isEmpty():
            return self.spark.createDataFrame([], "u bigint, v bigint")
        sets = self.sets(members.select(F.explode(F.array("pivot", "key")).alias("key")).distinct(), "dev").select("key", "full")
        heads = sets.select(F.col("key").alias("pivot"), F.col("full").alias("head"))
        both = members.join(sets, "key").join(heads, "pivot").select("pivot", "key", "n", "root", "main", "full", "head")
        dev = materialise(both.mapInArrow(_differences(self.num, self.den), "pivot bigint, key bigint, n int, root bigint, main bigint, token bigint, size int, pos int"), "dev", self.base)
        most = lambda a, b: F.floor((F.col(f"{a}.n") + F.col(f"{b}.n")) * (self.den - self.num) / F.lit(float(self.den + self.num)) + 1e-9)
        need = lambda a, b: F.ceil((F.col(f"{a}.size") + F.col(f"{b}.size") - most(a, b)) / 2)
        apart = (F.col("x.root") != F.col("y.root")) & (F.col("x.root") != F.col("x.main")) & ((F.col("y.root") == F.col("y.main")) | (F.col("x.key") < F.col("y.key")))
        fits = F.least("x.n", "y.n") * self.den >= F.greatest("x.n", "y.n") * self.num
        shared = dev.where("token is not null").alias("x").join(dev.where("token is not null").alias("y"), ["pivot", "token"]).where(apart & fits & (F.least(F.col("x.size") - F.col("x.pos"), F.col("y.size") - F.col("y.pos")) >= need("x", "y")))
        same = dev.where("size <= 2 and pos = 0").groupBy("pivot", "n", "size", "root").agg(F.min("key").alias("key"), F.first("main").alias("main"))
        once = dev.where("pos = 0")
        alike = same.alias("x").join(once.alias("y"), "pivot").where((F.col("x.root") != F.col("y.root")) & fits & (need("x", "y") <= 0))
        pair = [F.least("x.key", "y.key").alias("u"), F.greatest("x.key", "y.key").alias("v")]
        return shared.select(*pair).unionByName(alike.select(*pair)).distinct()

    def near(self, pairs: DataFrame, name: str, times: int) -> DataFrame:
        """Pairs (u, v) that the sketches leave."""
        ends = pairs.select(F.explode(F.array("u", "v")).alias("key")).distinct()
        odd = materialise(self.odd.join(ends, "key").dropDuplicates(["key"]), f"{name}_odd", self.base)
        left, right = (odd.select(F.col("key").alias(x), F.col("n").alias(f"n{x}"), F.col("odd").alias(f"o{x}")) for x in "uv")
        both = pairs.join(right, "v").join(left, "u").select("u", "v", "nu", "ou", "nv", "ov")
        return materialise(both.mapInArrow(_close(self.num, self.den, times), "u bigint, v bigint"), f"{name}_near", self.base)

    def links(self, pairs: DataFrame, name: str) -> DataFrame:
        """Those pairs (u, v) of class keys whose sets are similar enough."""
        pairs = materialise(pairs, f"{name}_pairs", self.base)
        if pairs.isEmpty():
            return pairs
        pairs = self.near(pairs, name, 1)
        if pairs.isEmpty():
            return pairs
        want = pairs.select(F.col("u").alias("key")).unionByName(pairs.select(F.col("v").alias("key"))).distinct()
        sets = self.sets(want, name)
        kept = self.joined(pairs, sets, ("p2", "p3"), _meet, f"{name}_met")
        return self.joined(kept, sets, ("full",), _similar(self.num, self.den), f"{name}_links")

    def joined(self, pairs: DataFrame, sets: DataFrame, columns: tuple, test, name: str) -> DataFrame:
        """Pairs whose ends' ``columns`` pass; no other columns are read."""
        left, right = (sets.select(F.col("key").alias(x), *(F.col(c).alias(f"{c}_{x}") for c in columns)) for x in "uv")
        both = pairs.join(right, "v").join(left, "u").select("u", "v", *(f"{c}_{x}" for x in "uv" for c in columns))
        return materialise(both.mapInArrow(_pairs_that(test), "u bigint, v bigint"), name, self.base)

    def run(self) -> DataFrame:
        entries = self.docs.select("text").mapInArrow(_entries(self.k, self.num, self.den, self.level), "token bigint, key bigint, n int, pos int, central int")
        entries = materialise(entries, "entries", self.base)
        me = F.struct("key", "n", "pos")
        most = F.struct("central", F.bitwise_not("key").alias("order"), "key", "n", "pos")
        buckets = entries.groupBy("token").agg(F.max(most).alias("most"), F.min("key").alias("low"), F.max("key").alias("high")).where("low <> high")
        heads = materialise(buckets.select("token", F.struct("most.key", "most.n", "most.pos").alias("head")), "heads", self.base)
        live = materialise(entries.join(heads, "token").select("token", me.alias("a"), "head"), "live", self.base)
        remove(self.spark, f"{self.base}/entries")
        star = live.where((F.col("a.key") != F.col("head.key")) & self.possible("a", "head")).select(F.col("head.key").alias("u"), F.col("a.key").alias("v")).distinct()
        links = self.links(star, "star")
        roots = materialise(connected_components(links), "roots1", self.base)
        # what the stars have left apart
        placed = live.join(roots, F.col("a.key") == F.col("node"), "left").select("token", "a", F.col("head.key").alias("pivot"), F.coalesce("root", "a.key").alias("root")).dropDuplicates(["token", "a"])
        sizes = placed.groupBy("token", "root").agg(F.count("*").alias("rows"))
        main = sizes.groupBy("token").agg(F.max_by("root", F.struct("rows", "root")).alias("main"), F.count("*").alias("roots"), F.sum("rows").alias("members")).where("roots > 1").select("token", "main", "members")
        mixed = materialise(placed.join(main, "token"), "mixed", self.base)
        large = materialise(mixed.where(F.col("members") > BUCKET).select(F.col("pivot").alias("u"), F.col("a.key").alias("v")).distinct(), "large", self.base)
        alike = self.near(large, "large", 2).select(F.col("u").alias("pivot"), F.col("v").alias("_key"), F.lit(True).alias("alike"))
        kind = materialise(mixed.join(alike, (mixed["pivot"] == alike["pivot"]) & (F.col("a.key") == F.col("_key")), "left").select(mixed["token"], "a", mixed["pivot"], "root", "main", ((F.col("members") > BUCKET) & F.col("alike").isNotNull()).alias("alike")), "kind", self.base)
        rest = kind.where("root <> main").select("token", "a", F.col("root").alias("ra"), "alike")
        every = kind.select("token", F.col("a").alias("b"), F.col("root").alias("rb"), "main", "alike")
        direct = rest.where("not alike").drop("alike").join(every.drop("alike"), "token").unionByName(rest.where("alike").drop("alike").join(every.where("not alike").drop("alike"), "token"))
        cross = (
            direct.where((F.col("ra") != F.col("rb")))
            .where(self.possible("a", "b"))
            .select(F.least("a.key", "b.key").alias("u"), F.greatest("a.key", "b.key").alias("v"))
        )
        cross = cross.unionByName(self.deviating(kind.where("alike"))).distinct()
        done = star.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
        more = self.links(cross.join(done, ["u", "v"], "left_anti"), "cross")
        if not more.isEmpty():
            # contract: edges between first-round roots only
            edges = links.unionByName(more)
            roots = materialise(connected_components(edges), "roots2", self.base)
        placed = self.members.join(roots, self.members["key"] == roots["node"], "left").select("doc_id", "n", F.when(F.col("n") > 0, F.coalesce("root", "key")).alias("root"))
        # written, so that the join back is one of its own and may split a hot root
        smallest = materialise(placed.where("n > 0").groupBy("root").agg(F.min("doc_id").alias("low")), "smallest", self.base)
        return placed.join(smallest, "root", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("low", "doc_id").alias("component_id"))


def jaccard_components(docs: DataFrame, shingle: int = 5, num: int = 80, den: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row: texts are linked when
    den * intersection >= num * union of their sets of ``shingle``-word runs."""
    return _Join(docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text")), shingle, num, den).run()


def keep_one(docs: DataFrame, shingle: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """All columns of the rows that are the smallest id of their group; rows
    repeated under one id stay or go together."""
    kept = jaccard_components(docs, shingle, num, den).where("doc_id <=> component_id").select(F.col("doc_id").alias("_kept")).distinct()
    return docs.join(kept, docs["doc_id"].eqNullSafe(kept["_kept"]), "left_semi").select(*docs.columns)
