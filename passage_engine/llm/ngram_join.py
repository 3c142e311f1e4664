"""Jaccard join of documents on word shingles, by prefix filters under several global orders.

How it scales:
* Equal texts meet by a hash of the text before any shingle is made, equal sets by a fingerprint.
* All orders put tokens of one class first (a bitmap of bounded size tells most of them), then rare
  ones, then frequent ones by their corpus frequency (counted over all documents; the most frequent
  are in a table of bounded size). Ties are broken by another hash in each order.
* A pair must share a prefix token under every order. The prefix of order 0 deals the classes out by
  token; a posting carries its place in that prefix and bit signatures of the prefixes of the other
  orders, so that the filters of all orders are applied inside a token's group, before a pair is made.
* Places bound the intersection: of two classes whose first common token leaves too few tokens
  behind it no pair is made. As tokens of one class stand first, unlike documents that only share a
  frequent passage fail here, and a group gives few pairs beside those that link.
* A token's group of up to ``small_group`` classes gives its pairs. A larger one gives a star and
  some rings; what they link is contracted. Its members then meet again by classes of size, in blocks
  of bounded size; only members of different components give pairs. Groups of very frequent tokens
  are dealt out by a salt at first; all their members, also one alone under its salt, meet again.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import runs, small_batches, stored, texts_of
from .graph import components
from .shingles import U, mix, shingle_sets

#: Frequencies are counted for the upper bits of tokens; sets and postings hold all 64 bits.
COUNT_BITS = 40
CHUNK = 1 << 17
ORDER_SEEDS = (0x51ED270B, 0x2545F491, 0x6C8E9CF5)


def pack(tokens: np.ndarray) -> bytes:
    """Sorted tokens as compressed differences."""
    d = np.diff(tokens, prepend=U(0))
    return zstandard.ZstdCompressor(1).compress(d.view(np.uint8).reshape(-1, 8).T.tobytes())


def unpack(blob: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(blob), np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view(np.uint64).ravel(), dtype=np.uint64)


def fingerprints(sets: list[np.ndarray]) -> list[int]:
    """64-bit hashes of whole sets; 0 for the empty one."""
    sizes = np.array([len(s) for s in sets], np.int64)
    sums = np.zeros(len(sets), np.uint64)
    full = np.flatnonzero(sizes)
    if len(full):
        starts = np.concatenate([[0], np.cumsum(sizes[full])[:-1]])
        sums[full] = np.add.reduceat(mix(np.concatenate([sets[i] for i in full])), starts)
    return (sums ^ sizes.astype(np.uint64)).view(np.int64).tolist()


def least_shared(n, m, percent: int):
    """The smallest intersection of sets of n and m tokens that link."""
    return -(-percent * (n + m) // (100 + percent))


class Orders:
    """The global orders: (shared or not, frequency of a frequent token or 0, hash of the order)."""

    def __init__(self, tokens: np.ndarray, counts: np.ndarray, segments: list[bytes]):
        by = np.argsort(tokens)
        self.tokens, self.counts = tokens[by], counts[by]
        self.n, self.width = len(segments), len(segments[0]) * 8
        self.bits = np.frombuffer(b"".join(segments), np.uint8)

    @staticmethod
    def place(tokens: np.ndarray, width: int) -> np.ndarray:
        return mix(tokens) % U(width)

    def rank(self, tokens: np.ndarray) -> np.ndarray:
        """0 for a token that only one class has, 1 for one that more may have, else its frequency."""
        short = tokens >> U(64 - COUNT_BITS)
        at = ((short * U(self.n)) >> U(COUNT_BITS)) * U(self.width) + self.place(short, self.width)
        rank = ((self.bits[(at >> U(3)).astype(np.int64)] >> (at & U(7)).astype(np.uint8)) & np.uint8(1)).astype(np.int64)
        shared = np.flatnonzero(rank)
        if len(self.tokens) and len(shared):
            mine = short[shared]
            at = np.minimum(np.searchsorted(self.tokens, mine), len(self.tokens) - 1)
            rank[shared] = np.where(self.tokens[at] == mine, self.counts[at], 1)
        return rank

    @staticmethod
    def prefix(tokens: np.ndarray, rank: np.ndarray, order: int, percent: int) -> tuple[np.ndarray, np.ndarray]:
        """Shared tokens of the prefix as places in ``tokens``, and their places in the order."""
        n = len(tokens)
        size = n - (n * percent + 99) // 100 + 1
        shared = np.flatnonzero(rank)
        size -= n - len(shared)
        if size <= 0:
            return shared[:0], shared[:0]
        by = shared[np.lexsort((mix(tokens[shared] ^ U(ORDER_SEEDS[order])), rank[shared]))[:size]]
        return by, np.arange(n - len(shared), n - len(shared) + len(by))


def _sets(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[tuple[pa.RecordBatch, int, list[np.ndarray], list[int]]]:
    """(batch, first row, sets of sorted tokens, their fingerprints) of a few documents at a time."""
    for b in batches:
        texts = texts_of(b)
        for i, j in runs(texts, CHUNK):
            found = shingle_sets(texts[i:j], k)
            yield b, i, found, fingerprints(found)


def _blobs(k: int, parts: int, flush: int = 1 << 20):
    """The tokens of a task's distinct classes, as a blob for each range of tokens."""

    def packed(held: list[np.ndarray]) -> pa.RecordBatch:
        t = np.sort(np.concatenate(held))
        cuts = np.searchsorted(t, np.array([((p << COUNT_BITS) + parts - 1) // parts for p in range(parts + 1)], np.uint64))
        rows = [(p, pack(t[a:b])) for p, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)) if b > a]
        return pa.record_batch([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], names=["part", "tokens"])

    def run(batches):
        seen, held, size = set(), [], 0
        for _, _, sets, fps in _sets(batches, k):
            for t, fp in zip(sets, fps, strict=True):
                if len(t) and fp not in seen:
                    seen.add(fp)
                    held.append(t >> U(64 - COUNT_BITS))
                    size += len(t)
            if size >= flush:
                yield packed(held)
                held, size = [], 0
        if held:
            yield packed(held)

    return run


def _frequencies(parts: int, bitmap_bytes: int, most: int, least_count: int):
    width = max(8, bitmap_bytes * 8 // parts // 8 * 8)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        t = np.sort(np.concatenate([unpack(b) for b in pdf.tokens]))
        at = np.flatnonzero(np.concatenate([[True], t[1:] != t[:-1]]))
        token, count = t[at], np.diff(np.append(at, len(t)))
        bits = np.zeros(width, bool)
        bits[Orders.place(token[count > 1], width).astype(np.int64)] = True
        often = np.flatnonzero(count >= least_count)
        if len(often) > -(-4 * most // parts):
            often = often[np.argpartition(-count[often], -(-4 * most // parts))[: -(-4 * most // parts)]]
        return pd.DataFrame({"part": [int(pdf.part.iloc[0])], "bits": [np.packbits(bits, bitorder="little").tobytes()], "token": [token[often].tobytes()], "times": [count[often].astype(np.int64).tobytes()]})

    return run, width // 8


def corpus_orders(docs: DataFrame, words: int, parts: int, bitmap_bytes: int = 1 << 23, most: int = 200_000, least_count: int = 8) -> Orders:
    """Frequencies over all documents; what comes to the driver is bounded by the last three parameters."""
    run, width = _frequencies(parts, bitmap_bytes, most, least_count)
    rows = docs.mapInArrow(_blobs(words, parts), "part int, tokens binary").groupBy("part").applyInPandas(run, "part int, bits binary, token binary, times binary").collect()
    segments = [bytes(width)] * parts
    for r in rows:
        segments[r.part] = bytes(r.bits)
    token = np.concatenate([np.zeros(0, np.uint64), *(np.frombuffer(r.token, np.uint64) for r in rows)])
    times = np.concatenate([np.zeros(0, np.int64), *(np.frombuffer(r.times, np.int64) for r in rows)])
    top = np.argsort(-times, kind="stable")[:most]
    return Orders(token[top], times[top], segments)


#: A row for each document (token null) and for each token of a class's prefix (doc_id null).
PROFILE = "doc_id long, h long, g long, token long, salt int, fp long, n int, place int, rare int, sig1 long, sig2 long"
POSTING = ("token", "salt", "fp", "n", "place", "rare", "sig1", "sig2")


def _profile(k: int, percent: int, orders, salt_at: int):
    def documents(rows: list[tuple]) -> pa.RecordBatch:
        cols = dict(zip(("doc_id", "h", "g", "fp", "n"), map(list, zip(*rows, strict=True)), strict=True))
        none = [None] * len(rows)
        kinds = {"salt": pa.int32(), "n": pa.int32(), "place": pa.int32(), "rare": pa.int32()}
        names = [c.split()[0] for c in PROFILE.split(", ")]
        return pa.record_batch([pa.array(cols.get(c, none), kinds.get(c, pa.int64())) for c in names], names=names)

    def postings(held: list[dict]) -> pa.RecordBatch:
        cols = {c: np.concatenate([x[c] for x in held]) for c in POSTING}
        none = pa.nulls(len(cols["fp"]), pa.int64())
        names = [c.split()[0] for c in PROFILE.split(", ")]
        return pa.record_batch([pa.array(cols[c]) if c in cols else none for c in names], names=names)

    def posting(t: np.ndarray, rank: np.ndarray, fp: int) -> dict:
        first, place = orders.value.prefix(t, rank, 0, percent)
        sigs = [np.bitwise_or.reduce(U(1) << (mix(t[orders.value.prefix(t, rank, o, percent)[0]]) & U(63))).view(np.int64) for o in (1, 2)]
        often, m = rank[first], len(first)
        # 0: not dealt out; parts of a token that is have salts from 1
        dealt = often // salt_at + 1
        salts = np.where(dealt > 1, mix(t[first] ^ np.int64(fp).view(np.uint64)) % dealt.astype(np.uint64) + U(1), U(0)).astype(np.int32)
        rare = int((rank <= 1).sum())
        return {"token": t[first].view(np.int64), "salt": salts, "fp": np.full(m, fp), "n": np.full(m, len(t), np.int32), "place": place.astype(np.int32), "rare": np.full(m, rare, np.int32), "sig1": np.full(m, sigs[0]), "sig2": np.full(m, sigs[1])}

    def run(batches):
        seen: set[int] = set()
        held, size, rows = [], 0, []
        for b, i, sets, fps in _sets(batches, k):
            ids = [b.column(c).slice(i, len(sets)).to_pylist() for c in ("doc_id", "h", "g")]
            rows += zip(*ids, fps, map(len, sets), strict=True)
            fresh = []
            for x, (t, fp, doc) in enumerate(zip(sets, fps, ids[0], strict=True)):
                if len(t) and doc is not None and fp not in seen:
                    seen.add(fp)
                    fresh.append(x)
            if fresh:
                sizes = np.array([len(sets[x]) for x in fresh], np.int64)
                ends = np.cumsum(sizes)
                ranks = orders.value.rank(np.concatenate([sets[x] for x in fresh]))
                shared = np.add.reduceat(ranks > 0, ends - sizes, dtype=np.int64)
                # tokens of one class alone fill the prefix of most documents
                for at in np.flatnonzero(shared >= -(-sizes * percent // 100)):
                    got = posting(sets[fresh[at]], ranks[ends[at] - sizes[at] : ends[at]], fps[fresh[at]])
                    held.append(got)
                    size += len(got["fp"])
            if len(rows) >= 5000:
                yield documents(rows)
                rows = []
            if size > 50_000:
                yield postings(held)
                held, size = [], 0
        if rows:
            yield documents(rows)
        if held:
            yield postings(held)

    return run


GROUPED = "token long, a long, b long, n int, place int, sig1 long, sig2 long"


def _may_link(percent: int, n, place, sig1, sig2, i, j) -> np.ndarray:
    """Whether pairs (i, j) that share a token at these places pass the filters of all orders."""
    need = least_shared(n[i], n[j], percent)
    return (n[i] - place[i] >= need) & (n[j] - place[j] >= need) & (np.minimum(n[i], n[j]) >= need) & (sig1[i] & sig1[j] != 0) & (sig2[i] & sig2[j] != 0)


def _buffered(batches: Iterator[pa.RecordBatch], keys: int, rows: int = 100_000) -> Iterator[list[np.ndarray]]:
    """Columns of sorted batches in pieces of about ``rows`` rows; rows of one key stay together."""
    held: list[list[np.ndarray]] = []
    size = 0

    def joined():
        return [np.concatenate(c) for c in zip(*held, strict=True)]

    for b in batches:
        if not b.num_rows:
            continue
        held.append([c.to_numpy(zero_copy_only=False) for c in b.columns])
        size += b.num_rows
        if size < rows:
            continue
        cols = joined()
        last = np.logical_or.reduce([c != c[-1] for c in cols[:keys]])
        cut = int(np.flatnonzero(last)[-1]) + 1 if last.any() else 0
        if cut:
            yield [c[:cut] for c in cols]
        held = [[c[cut:] for c in cols]]
        size = 0  # a group beyond the buffer is joined again only after as many rows more
    if held:
        cols = joined()
        if len(cols[0]):
            yield cols


def _bounds(cols: list[np.ndarray], keys: int) -> np.ndarray:
    new = np.logical_or.reduce([c[1:] != c[:-1] for c in cols[:keys]])
    return np.concatenate([[0], np.flatnonzero(new) + 1, [len(cols[0])]])


def _groups(percent: int, small: int, ring_every: int):
    """Sorted postings to pairs (token null) and to the members of larger or dealt-out groups (b null)."""

    def larger(token: int, fp, rare, every: bool):
        pivot = int(np.lexsort((fp, rare))[0])
        rest = np.delete(np.arange(len(fp)), pivot)
        i, j = np.full(len(rest), pivot), rest
        if every:
            by = np.argsort(mix(fp.view(np.uint64) ^ np.int64(token).view(np.uint64)))
            i, j = np.concatenate([i, by]), np.concatenate([j, np.roll(by, 1)])
        return i, j

    def run(batches):
        for cols in _buffered(batches, 2):
            token, salt, fp = cols[:3]
            # a class that several tasks posted counts once
            once = np.concatenate([[True], (token[1:] != token[:-1]) | (salt[1:] != salt[:-1]) | (fp[1:] != fp[:-1])])
            cols = [c[once] for c in cols]
            token, salt, fp, n, place, rare, sig1, sig2 = cols
            n, place = n.astype(np.int64), place.astype(np.int64)
            bounds = _bounds(cols, 2)
            size = np.diff(bounds)
            group = np.repeat(np.arange(len(size)), size)
            left, right = [], []
            few = size[group] <= small
            for step in range(1, small):
                i = np.flatnonzero(few[:-step] & (group[:-step] == group[step:])) if step < len(group) else np.zeros(0, np.int64)
                left.append(i)
                right.append(i + step)
            for g in np.flatnonzero(size > small):
                s, e = bounds[g], bounds[g + 1]
                i, j = larger(int(token[s]), fp[s:e], rare[s:e], int(mix(token[s : s + 1].view(np.uint64))[0]) % ring_every == 0)
                left.append(i + s)
                right.append(j + s)
            i, j = np.concatenate([np.zeros(0, np.int64), *left]), np.concatenate([np.zeros(0, np.int64), *right])
            ok = _may_link(percent, n, place, sig1, sig2, i, j) & (fp[i] != fp[j])
            a, b = np.minimum(fp[i[ok]], fp[j[ok]]), np.maximum(fp[i[ok]], fp[j[ok]])
            pairs = np.unique(np.stack([a, b]), axis=1) if len(a) else np.zeros((2, 0), np.int64)
            none = pa.nulls(pairs.shape[1], pa.int64())
            short = pa.nulls(pairs.shape[1], pa.int32())
            names = [c.split()[0] for c in GROUPED.split(", ")]
            yield pa.record_batch([none, pa.array(pairs[0]), pa.array(pairs[1]), short, short, none, none], names=names)
            m = (size[group] > small) | (salt > 0)
            yield pa.record_batch([pa.array(token[m]), pa.array(fp[m]), pa.nulls(int(m.sum()), pa.int64()), pa.array(n[m].astype(np.int32)), pa.array(place[m].astype(np.int32)), pa.array(sig1[m]), pa.array(sig2[m])], names=names)

    return run


def _apart(percent: int, cells: int = 1 << 18):
    """Members of one token, class of size and pair of blocks to pairs of different components.

    home is 1 for a member of the class itself and 0 for a smaller one that a member may link with;
    of a block pair (i, j) home members of one block meet all members of the other.
    """

    def run(batches):
        for cols in _buffered(batches, 4):
            bounds = _bounds(cols, 4)
            own, home, fp, n, place, root, sig1, sig2 = (c.astype(np.int64) for c in cols[4:])
            found = []
            for s, e in zip(bounds[:-1], bounds[1:], strict=True):
                if root[s:e].min() == root[s:e].max():
                    continue
                block_i, block_j = cols[2][s], cols[3][s]
                step = max(1, cells // (e - s))
                for x in range(s, e, step):
                    mine = np.arange(x, min(x + step, e))
                    mine = mine[home[mine] == 1]
                    i, j = np.repeat(mine, e - s), np.tile(np.arange(s, e), len(mine))
                    ok = (root[i] != root[j]) & (n[i] * percent <= 100 * n[j]) & (n[j] * percent <= 100 * n[i])
                    i, j = i[ok], j[ok]
                    ok = _may_link(percent, n, place, sig1, sig2, i, j) & ((home[j] == 0) | (fp[i] < fp[j])) & ((block_i == block_j) | (own[i] != own[j]))
                    found.append(np.stack([np.minimum(fp[i[ok]], fp[j[ok]]), np.maximum(fp[i[ok]], fp[j[ok]])]))
            if found:
                pairs = np.unique(np.concatenate(found, axis=1), axis=1)
                yield pa.record_batch([pa.array(pairs[0]), pa.array(pairs[1])], names=["a", "b"])

    return run


def _tokens(k: int):
    def run(batches):
        rows, size = [], 0

        def out():
            return pa.record_batch([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.binary())], names=["doc_id", "fp", "tokens"])

        for b, i, sets, fps in _sets(batches, k):
            rows += zip(b.column("doc_id").slice(i, len(sets)).to_pylist(), fps, [t.tobytes() for t in sets], strict=True)
            size += sum(map(len, sets))
            if size > 1 << 18:
                yield out()
                rows, size = [], 0
        if rows:
            yield out()

    return run


def _verify(percent: int, orders):
    """Pairs with both sets to links: the filters of the further orders, then the exact measure."""

    def shares(x, y, ranks, order):
        p, q = (t[orders.value.prefix(t, r, order, percent)[0]] for t, r in zip((x, y), ranks, strict=True))
        return len(np.intersect1d(p, q, assume_unique=True)) > 0

    def run(batches):
        for b in batches:
            kept = []
            for i, (x, y) in enumerate(zip(b.column("x"), b.column("y"), strict=True)):
                x, y = (np.frombuffer(v.as_buffer(), np.uint64) for v in (x, y))
                ranks = [orders.value.rank(t) for t in (x, y)]
                if all(shares(x, y, ranks, o) for o in range(1, len(ORDER_SEEDS))):
                    both = len(np.intersect1d(x, y, assume_unique=True))
                    if 100 * both >= percent * (len(x) + len(y) - both):
                        kept.append(i)
            yield b.select(["a", "b"]).take(pa.array(kept, pa.int64()))

    return run


def similarity_components(docs: DataFrame, words: int = 5, percent: int = 75, small_group: int = 6, ring_every: int = 8, salt_at: int = 20_000, block: int = 4096, most_broadcast: int = 1_000_000) -> DataFrame:
    """Documents (doc_id, text) to (doc_id, n_shingles, component_id).

    Two documents link when 100 * |intersection| >= percent * |union| of their shingle sets;
    component_id is the smallest doc_id that links reach. Null text is empty; a document without
    words links with nothing and is its own component. Rows without doc_id get a null component_id
    and link nothing. Repeated rows stay, each with its result; rows that repeat a doc_id with
    another text are one document as far as links go. Other columns are not read. Tokens are
    64-bit hashes of shingles; equal texts are told by two 64-bit hashes, equal sets by one.
    Ids are broadcast while there are at most ``most_broadcast`` of them (16 bytes each).
    """
    spark = small_batches(docs.sparkSession)
    parts = max(8, int(spark.conf.get("spark.sql.shuffle.partitions")))
    hashed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumns({"h": F.xxhash64(F.coalesce("text", F.lit(""))), "g": F.xxhash64(F.lit("second"), F.coalesce("text", F.lit("")))})

    def small(df: DataFrame) -> DataFrame:
        return F.broadcast(df) if df.count() <= most_broadcast else df

    # Of rows with equal texts only those of the smallest doc_id go on.
    ids = stored(hashed.select("doc_id", "h", "g"), "hashed")
    first = stored(ids.groupBy("h", "g").agg(F.min("doc_id").alias("least"), F.count("*").alias("copies")).where("copies > 1").select("h", "g", "least"), "copied")
    again = stored(ids.join(first, ["h", "g"]).where("doc_id <> least").select("doc_id", "h", "g").distinct(), "again")
    known = hashed.join(small(again), ["doc_id", "h", "g"], "left_anti").select("doc_id", "text", "h", "g")

    orders = spark.sparkContext.broadcast(corpus_orders(known.where("doc_id is not null").select("text"), words, parts))
    profile = stored(known.mapInArrow(_profile(words, percent, orders, salt_at), PROFILE), "profile")
    rows = profile.where("token is null").select("doc_id", "h", "g", "fp", "n")
    classes = stored(rows.where("n > 0 and doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("least")), "classes")

    postings = profile.where("token is not null").select(*POSTING)
    grouped = stored(postings.repartition(parts, "token", "salt").sortWithinPartitions("token", "salt", "fp").mapInArrow(_groups(percent, small_group, ring_every), GROUPED), "grouped")
    pairs = stored(grouped.where("b is not null").select("a", "b").distinct(), "pairs")

    def verified(found: DataFrame) -> DataFrame:
        """Pairs of fingerprints to links of doc_ids; only the texts of the pairs are read again."""
        fps = found.select(F.col("a").alias("fp")).union(found.select("b")).distinct()
        wanted = stored(classes.join(fps, "fp", "left_semi").select(F.col("least").alias("doc_id")).distinct(), "wanted")
        sets = stored(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(small(wanted), "doc_id", "left_semi").mapInArrow(_tokens(words), "doc_id long, fp long, tokens binary"), "sets")
        one = sets.select(F.col("doc_id").alias("da"), F.col("fp").alias("a"), F.col("tokens").alias("x"))
        two = sets.select(F.col("doc_id").alias("db"), F.col("fp").alias("b"), F.col("tokens").alias("y"))
        near = found.join(one, "a").join(two, "b").select(F.col("da").alias("a"), F.col("db").alias("b"), "x", "y")
        return stored(near.mapInArrow(_verify(percent, orders), "a long, b long"), "links")

    links = verified(pairs)
    roots = components(links)
    place = stored(classes.join(roots, classes.least == roots.node, "left").select("fp", "least", F.coalesce("root", "least").alias("root")), "place")
    # What stars and rings left apart: members of other components in the same group. A class of size
    # spans a little more than the ratio of sizes that may link, so that two neighbours meet.
    width = float(np.log(101.0 / percent))
    at = F.floor(F.log(F.col("n").cast("double")) / F.lit(width)).cast("int")
    reach = F.floor((F.col("n") - F.col("place")) * F.lit((100 + percent) / percent)) - F.col("n") + 1
    members = grouped.where("b is null").select("token", F.col("a").alias("fp"), "n", "place", "sig1", "sig2").join(place.select("fp", "root"), "fp").withColumn("at", at)
    mixed = stored(members.groupBy("token").agg(F.min("root").alias("x"), F.max("root").alias("y")).where("x < y").select("token"), "mixed")
    members = members.join(mixed, "token", "left_semi")
    above = F.floor(F.log(F.greatest(reach, F.lit(1)).cast("double")) / F.lit(width)).cast("int") > F.col("at")
    met = stored(members.withColumn("meet", F.when(above, F.array("at", F.col("at") + 1)).otherwise(F.array("at"))).withColumn("meet", F.explode("meet")).withColumn("home", (F.col("at") == F.col("meet")).cast("int")), "met")
    crowded = stored(met.groupBy("token", "meet").agg(F.count("*").alias("size")).where(F.col("size") > block).select("token", "meet", F.ceil(F.col("size") / block).cast("int").alias("blocks")), "crowded")
    dealt = met.join(crowded, ["token", "meet"], "left").withColumn("blocks", F.coalesce("blocks", F.lit(1))).withColumn("own", F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")})
    dealt = dealt.select("token", "meet", "i", "j", "own", "home", "fp", "n", "place", "root", "sig1", "sig2").repartition(parts, "token", "meet", "i", "j").sortWithinPartitions("token", "meet", "i", "j")
    more = stored(dealt.mapInArrow(_apart(percent), "a long, b long").distinct().join(pairs, ["a", "b"], "left_anti"), "more")
    if not more.isEmpty():
        links = links.union(verified(more))
        roots = components(links)
        place = stored(classes.join(roots, classes.least == roots.node, "left").select("fp", "least", F.coalesce("root", "least").alias("root")), "place")
    of = stored(rows.join(place, "fp", "left").groupBy("h", "g").agg(F.max("n").alias("n"), F.min("root").alias("root")), "texts")
    component = F.when(F.col("n") > 0, F.col("root")).otherwise(F.col("doc_id"))
    return ids.join(of, ["h", "g"], "left").select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), component).alias("component_id"))


def representatives(docs: DataFrame, most_broadcast: int = 500_000, **options) -> DataFrame:
    """The rows of one document of each component, the one of smallest doc_id, with all columns.

    Of rows that repeat a doc_id one stays; rows without doc_id all stay. The ids that go are
    broadcast while there are at most ``most_broadcast`` of them, so that texts need no shuffle;
    beyond that the same join shuffles.
    """
    found = stored(similarity_components(docs, **options).where("doc_id is not null"), "components")
    by_id = stored(found.groupBy("doc_id").agg(F.count("*").alias("rows"), F.max((F.col("doc_id") != F.col("component_id")).cast("int")).alias("linked")).where("rows > 1 or linked = 1"), "odd-ids")
    n = by_id.count()
    small = F.broadcast if n <= most_broadcast else lambda df: df
    kept = docs.join(small(by_id.select("doc_id")), "doc_id", "left_anti")
    again = by_id.where("linked = 0").select("doc_id")
    return kept if again.isEmpty() else kept.unionByName(docs.join(small(again), "doc_id", "left_semi").dropDuplicates(["doc_id"]))
