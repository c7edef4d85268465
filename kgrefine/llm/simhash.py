"""SimHash fingerprints, a byte-position inverted index with count filtering, and groups of linked texts."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgrefine.plans.components import connected_components
from kgrefine.plans.scratch import written

from .vocabulary import free_name, slices

BITS = 64
#: Any five of eight byte places hold three places of one half, so these eight triples meet every pair with five equal bytes.
TRIPLES = tuple(t for half in ((0, 1, 2, 3), (4, 5, 6, 7)) for t in combinations(half, 3))


def shingles(text: str | None, words: int) -> list[bytes]:
    """The text's word shingles, A-Z lowered, repeats kept; the whole sequence if it is shorter; none without words."""
    found = (text or "").encode().lower().split()
    if len(found) <= words:
        return [b" ".join(found)] if found else []
    return [b" ".join(s) for s in zip(*(found[i:] for i in range(words)), strict=False)]


def bit_counts(h: np.ndarray) -> np.ndarray:
    """How many rows of (n, w) unsigned 64-bit words have each of the 64 * w bits; carry-save adders, then a plain count."""
    total, weight = np.zeros(64 * h.shape[1], dtype=np.int64), 1
    while len(h):
        carried = []
        while len(h) * h.shape[1] >= 1024 and len(h) >= 3:
            k = len(h) // 3
            a, b, c = h[:k], h[k : 2 * k], h[2 * k : 3 * k]
            x = a ^ b
            carried.append((a & b) | (x & c))
            h = np.concatenate([x ^ c, h[3 * k :]])
        total += weight * np.unpackbits(h.view(np.uint8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        h, weight = (np.concatenate(carried) if carried else h[:0]), 2 * weight
    return total


def digests(parts, chunk: int = 100_000):
    """XXH64 (seed 42) of the parts, in bounded arrays."""
    digest, parts = xxhash.xxh64_intdigest, list(parts)
    for at in range(0, len(parts), chunk):
        yield np.array([digest(p, 42) for p in parts[at : at + chunk]], dtype="<u8")


def fingerprint(parts: list[bytes]) -> int:
    """64 bits, each set where more than half of the parts' XXH64 (seed 42) have it; 0 without parts. Signed."""
    if not parts:
        return 0
    tally = sum(bit_counts(h[:, None]) for h in digests(parts))
    return int(np.packbits(2 * tally > len(parts), bitorder="little").view("<i8")[0])


def fingerprints(docs: DataFrame, words: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp long) of whole texts."""

    def go(batches):
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([fingerprint(shingles(t, words)) for t in b.column(1).to_pylist()], pa.int64())], ["doc_id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text_col).mapInArrow(go, "doc_id long, fp long")


def unequal_bytes(x: np.ndarray) -> np.ndarray:
    """How many of the eight bytes of each xor are not zero."""
    for shift in (4, 2, 1):
        x = x | (x >> np.uint64(shift))
    return np.bitwise_count(x & np.uint64(0x0101010101010101))


def within(x: np.ndarray, y: np.ndarray, distance: int, counted: bool) -> np.ndarray:
    """Whether the xors of both words hold at most ``distance`` bits; ``counted`` first asks for 8 - distance shared bytes of the first."""
    out = unequal_bytes(x) <= distance if counted else np.ones(x.shape, dtype=bool)
    out[out] = np.bitwise_count(x[out]).astype(np.int16) + np.bitwise_count(y[out]) <= distance
    return out


def forest(a: np.ndarray, b: np.ndarray, node: np.ndarray, side: np.ndarray | None, distance: int, counted: bool, step: int = 64) -> list[tuple[np.ndarray, np.ndarray]]:
    """Edges that span the groups of linked fingerprints of one list: every pair is compared, at most one edge a row is kept.

    ``side`` limits links to rows of two different sides (a list dealt out in pairs of chunks).
    """
    out, left = [], np.ones(len(a), dtype=bool)
    while left.any():
        seed = int(np.argmax(left))
        left[seed] = False
        queue = np.array([seed])
        while len(queue):
            now, queue = queue[:step], queue[step:]
            rest = np.flatnonzero(left)
            if not len(rest):
                return out
            hit = within(a[now][:, None] ^ a[rest][None, :], b[now][:, None] ^ b[rest][None, :], distance, counted)
            if side is not None:
                hit &= side[now][:, None] != side[rest][None, :]
            any_hit = hit.any(axis=0)
            if any_hit.any():
                found = rest[any_hit]
                out.append((node[now[hit[:, any_hit].argmax(axis=0)]], node[found]))
                left[found] = False
                queue = np.concatenate([queue, found])
    return out


def list_edges(index: DataFrame, distance: int, counted: bool, list_rows: int = 20_000) -> DataFrame:
    """(u, v): edges that span the linked rows of every list of an index (key, node, a, b).

    Each list's pairs are compared where its rows meet and only a spanning forest leaves, so a list of
    thousands of near copies gives as many rows as it has. A list over ``list_rows`` is dealt out in
    chunks and every pair of chunks is compared apart; a chunk pair is the most a task holds at once.
    """
    sizes = index.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    index = index.join(sizes, "key").withColumn("chunks", F.ceil(F.col("n") / list_rows).cast("int"))
    chunk = F.pmod(F.xxhash64("node", F.lit(5)), F.col("chunks")).cast("int")
    index = index.withColumn("c", chunk).withColumn("o", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    index = index.select("key", F.least("c", "o").alias("i"), F.greatest("c", "o").alias("j"), (F.col("c") > F.col("o")).cast("int").alias("side"), "a", "b", "node")
    dealt = index.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j", "side", "node")

    def work(cols):
        key, i, j, side, a, b, node = cols
        a, b = a.view(np.uint64), b.view(np.uint64)
        new = np.flatnonzero((key[1:] != key[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])) + 1
        starts, ends = np.concatenate([[0], new]), np.concatenate([new, [len(key)]])
        two = (ends - starts == 2) & (i[starts] == j[starts])
        at = starts[two]
        hit = within(a[at] ^ a[at + 1], b[at] ^ b[at + 1], distance, counted)
        edges = [(node[at[hit]], node[at[hit] + 1])]
        for s, e in zip(starts[~two], ends[~two], strict=True):
            if e - s > 1:
                edges += forest(a[s:e], b[s:e], node[s:e], None if i[s] == j[s] else side[s:e], distance, counted)
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate([e[k] for e in edges]), pa.int64()) for k in (0, 1)], ["u", "v"])

    def lists(batches):
        """Whole lists at a time; one that a batch cuts waits for its rest."""
        held: list[tuple] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(tuple(batch.column(c).to_numpy(zero_copy_only=False) for c in range(7)))
            last = tuple(held[-1][c][-1] for c in range(3))
            if all(held[0][c][0] == last[c] for c in range(3)):
                continue  # one list so far
            cols = tuple(np.concatenate([h[c] for h in held]) for c in range(7))
            cut = int(np.argmax((cols[0] == last[0]) & (cols[1] == last[1]) & (cols[2] == last[2])))
            held = [tuple(c[cut:] for c in cols)]
            yield work(tuple(c[:cut] for c in cols))
        if held:
            yield work(tuple(np.concatenate([h[c] for h in held]) for c in range(7)))

    return dealt.mapInArrow(lists, "u long, v long").distinct()


def similar_edges(nodes: DataFrame, distance: int = 3, list_rows: int = 20_000) -> DataFrame:
    """(u, v): edges that connect exactly the (node, fp) rows whose fingerprints link, directly or through others.

    Lists of the inverted index are keyed by three byte places and their values: a single place has 256
    lists whatever the input, so its lists' pairs grow with the square of the rows, while three places
    have 2**24 for each of the eight triples that meet every pair of at least five shared bytes. In a
    list, pairs must share the guaranteed 8 - ``distance`` positional bytes before their bits are checked.
    """
    if distance > 3:
        raise ValueError("the triples guarantee at most three differing bits")
    byte = [F.shiftrightunsigned("fp", 8 * p).bitwiseAND(F.lit(255)) for p in range(8)]
    keys = [F.lit(i << 24).cast("long") + byte[a] * 65536 + byte[b] * 256 + byte[c] for i, (a, b, c) in enumerate(TRIPLES)]
    index = nodes.select("node", F.col("fp").alias("a"), F.lit(0).cast("long").alias("b"), F.explode(F.array(*keys)).alias("key"))
    return list_edges(index, distance, True, list_rows)


def simhash_groups(docs: DataFrame, words: int = 3, distance: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp, component_id): whole-text fingerprints and the smallest doc_id reachable over links.

    Documents whose fingerprints are equal are one node before the search; nodes link at ``distance``
    or fewer differing bits. A null or blank text has fingerprint 0 and links like any other. Rows with
    a null doc_id get their fingerprint and, if they are alone, a null component. Repeated rows repeat.
    An empty table gives none. Further columns are not carried.
    """
    each = written(fingerprints(docs, words, id_col, text_col), "fp")
    nodes = written(each.groupBy("fp").agg(F.min("doc_id").alias("node")), "fp")
    groups = connected_components(similar_edges(nodes.where("node is not null"), distance))
    named = nodes.join(groups, "node", "left").select("fp", F.coalesce("component", "node").alias("component_id"))
    return each.join(named, "fp").select("doc_id", "fp", "component_id")


#: Lists a text stands in, each keyed by two byte places of its wide fingerprint; further words by which rows of a list are compared.
LISTS, CHECK_WORDS = 160, 2
PLACES = 2 * LISTS
#: Bits of the check words in which rows of a list may differ, and byte places of all that a pair must share before its texts are compared.
CHECK_BITS, SHARED_PLACES = 40, 20
_TURN = np.random.default_rng(11).integers(0, 2**63, PLACES // 8 + CHECK_WORDS, dtype=np.uint64)
_ODD = np.random.default_rng(12).integers(0, 2**63, PLACES // 8 + CHECK_WORDS, dtype=np.uint64) | np.uint64(1)


def wide_fingerprint(hashed: np.ndarray, chunk: int = 2_048) -> np.ndarray:
    """A SimHash of 42 words of a shingle set's hashes: each bit is 1 where more than half of the shingles have it.

    Two sets of one size and a Jaccard of j differ in arccos(2j / (1 + j)) / pi of the bits: 15 % at 0.8.
    """
    tally = np.zeros(64 * len(_ODD), dtype=np.int64)
    for at in range(0, len(hashed), chunk):
        h = (hashed[at : at + chunk, None].astype(np.uint64) ^ _TURN) * _ODD
        h ^= h >> np.uint64(32)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(29)
        tally += bit_counts(h)
    return np.packbits(2 * tally > len(hashed), bitorder="little").view("<u8")


def place_lists(fps: np.ndarray) -> np.ndarray:
    """(rows, LISTS): the lists of wide fingerprints, a number of 24 bits from the pair of places and their two bytes."""
    return np.ascontiguousarray(fps[:, : PLACES // 8]).view("<u2").astype(np.int64) + (np.arange(LISTS, dtype=np.int64) << 16)


def close_in_lists(lists: np.ndarray, node: np.ndarray, a: np.ndarray, b: np.ndarray, short: int = 64) -> list[tuple[np.ndarray, np.ndarray]]:
    """Edges that connect the rows of each list (whole lists, in order) that differ in at most ``CHECK_BITS`` bits.

    ``lists`` holds the list, the two chunks that meet in it and, lowest, the side of the row. Each group
    of a list is tied to its smallest node, which large groups have in common over many lists, so that
    their edges are mostly the same ones.
    """
    group, side, least, pairs = lists >> 1, lists & 1, node.copy(), [(np.zeros(0, dtype=np.int64),) * 2]
    cross = ((group >> 19) & 0x7FFFF) != (group & 0x7FFFF)
    starts = np.concatenate([[0], np.flatnonzero(group[1:] != group[:-1]) + 1])
    sizes = np.diff(np.concatenate([starts, [len(group)]]))
    left = np.repeat(starts + sizes, sizes) - np.arange(len(group))  # rows of the list from this one on
    at = np.flatnonzero(np.repeat(sizes <= short, sizes))
    for d in range(1, short):
        at = at[left[at] > d]
        if not len(at):
            break
        hit = within(a[at] ^ a[at + d], b[at] ^ b[at + d], CHECK_BITS, False) & (~cross[at] | (side[at] != side[at + d]))
        pairs.append((at[hit], at[hit] + d))
    p, q = (np.concatenate([x[k] for x in pairs]) for k in (0, 1))
    while (apart := least[p] != least[q]).any():  # as many rounds as a short list has rows at most
        low = np.minimum(least[p[apart]], least[q[apart]])
        np.minimum.at(least, p[apart], low)
        np.minimum.at(least, q[apart], low)
    for s, n in zip(starts[sizes > short], sizes[sizes > short], strict=True):
        rows = np.arange(s, s + n)
        if n <= 2_048:  # most rows of a chance list have no partner
            hit = within(a[rows][:, None] ^ a[rows][None, :], b[rows][:, None] ^ b[rows][None, :], CHECK_BITS, False)
            rows = rows[hit.sum(axis=1) > 1]
        if len(rows) > 1:
            root = np.arange(len(rows))
            for u, v in forest(a[rows], b[rows], np.arange(len(rows)), side[rows] if cross[s] else None, CHECK_BITS, False):
                root[v] = root[u]  # u was reached before
            low = node[rows].copy()
            np.minimum.at(low, root, node[rows])
            least[rows] = low[root]
    tied = least != node
    return [(least[tied], node[tied])]


def wide_edges(nodes: DataFrame, list_rows: int = 20_000) -> DataFrame:
    """(u, v): edges that connect the (node, fp binary) rows whose wide fingerprints meet in a list of the inverted index and are close.

    A pair at a Jaccard of exactly 0.8 has two given bytes in common with a chance of 0.072, so 6 in a
    million such pairs meet in none of the 160 lists. Every pair of a list is compared; lists that a
    sample of the nodes shows to be over ``list_rows`` are dealt out in chunks whose pairs are tasks apart.
    """
    def read(batch):
        return np.frombuffer(b"".join(batch.column(1).to_pylist()), dtype="<u8").reshape(batch.num_rows, -1)

    def sampled(batches):
        for batch in slices(batches):
            yield pa.RecordBatch.from_arrays([pa.array(place_lists(read(batch)).ravel())], ["list"])

    long, share = {}, 64
    if nodes.count() > list_rows:
        some = nodes.where(F.pmod(F.xxhash64("node", F.lit(7)), F.lit(share)) == 0).select("node", "fp").mapInArrow(sampled, "list long")
        found = some.groupBy("list").agg((F.count("*") * share).alias("n")).where(F.col("n") > list_rows)
        long = {r["list"]: -(-r["n"] // list_rows) for r in found.collect()}

    def put(batches):
        known = np.array(sorted(long), dtype=np.int64)
        for batch in slices(batches, 256):
            fps, node = read(batch), batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            lists, row = place_lists(fps).ravel(), np.repeat(np.arange(len(fps)), LISTS)
            dealt = np.isin(lists, known)
            cols = [(lists[~dealt] << 39, row[~dealt])]
            for k, r in zip(lists[dealt].tolist(), row[dealt].tolist(), strict=True):
                c, o = (int(node[r]) * 0x9E3779B97F4A7C15 >> 20) % long[k], np.arange(long[k], dtype=np.int64)
                cols.append((k << 39 | np.minimum(o, c) << 20 | np.maximum(o, c) << 1 | (c > o), np.full(len(o), r)))
            lists, row = (np.concatenate([c[x] for c in cols]) for x in (0, 1))
            check = fps[:, PLACES // 8 :].view("<i8")
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (lists, node[row], check[row, 0], check[row, 1])], ["list", "node", "a", "b"])

    def search(batches):
        """Whole lists at a time; one that a batch cuts waits for its rest."""
        held: list[list[np.ndarray]] = []
        for batch in batches:
            if batch.num_rows:
                held.append([batch.column(c).to_numpy(zero_copy_only=False) for c in range(4)])
                if held[0][0][0] >> 1 != held[-1][0][-1] >> 1:
                    cols = [np.concatenate([h[c] for h in held]) for c in range(4)]
                    cut = int(np.searchsorted(cols[0] >> 1, cols[0][-1] >> 1))
                    held = [[c[cut:] for c in cols]]
                    yield edges([c[:cut] for c in cols])
        if held:
            yield edges([np.concatenate([h[c] for h in held]) for c in range(4)])

    def edges(cols):
        lists, node, a, b = cols
        found = close_in_lists(lists, node, a.view(np.uint64), b.view(np.uint64))
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate([node[:0], *(e[k] for e in found)]), pa.int64()) for k in (0, 1)], ["u", "v"])

    index = nodes.select("node", "fp").mapInArrow(put, "list long, node long, a long, b long")
    found = index.repartition(F.shiftright("list", 1)).sortWithinPartitions("list").mapInArrow(search, "u long, v long")
    # a node has one smallest node a list at most; it keeps the least of them, and that one is tied to the others
    ties = found.groupBy("v").agg(F.min("u").alias("low"), F.array_append(F.collect_set("u"), F.col("v")).alias("all"))
    return ties.select(F.col("low").alias("u"), F.explode("all").alias("v")).where("u <> v").distinct()


def shingle_set(parts: list[bytes]) -> np.ndarray:
    """The distinct shingles' XXH64, sorted."""
    return np.unique(np.concatenate([np.zeros(0, dtype="<u8"), *digests(set(parts))]))


def alike(x: np.ndarray, y: np.ndarray, similarity: float) -> bool:
    """Whether the Jaccard similarity of two sorted sets is at least ``similarity``."""
    few, many = sorted((len(x), len(y)))
    if few < similarity * many * (1 - 1e-12):
        return False
    both = np.concatenate([x, y])
    both.sort()
    shared = int(np.count_nonzero(both[1:] == both[:-1]))
    return shared / (few + many - shared) >= similarity


def exact_forest(rows: list[tuple], similarity: float, two_sides: bool) -> list[tuple[int, int]]:
    """Edges that span the groups of alike sets among (node, side, keys, set, fp) rows.

    A pair is tested, on its whole sets, if it shares a key and, where rows have fingerprints, enough
    of their byte places; it is left untested only where both rows are already joined by alike pairs.
    ``two_sides`` limits tests to rows of different sides.
    """
    keys, sides = np.stack([r[2] for r in rows]), np.array([r[1] for r in rows])
    places = np.stack([np.frombuffer(r[4], dtype=np.uint8)[:PLACES] for r in rows]) if rows[0][4] is not None else None
    out, left = [], np.ones(len(rows), dtype=bool)
    for seed in range(len(rows)):
        if not left[seed]:
            continue
        left[seed] = False
        queue = [seed]
        while queue:
            now = queue.pop()
            rest = np.flatnonzero(left & (sides != sides[now])) if two_sides else np.flatnonzero(left)
            rest = rest[(keys[rest] == keys[now]).any(axis=1)]
            if places is not None:
                rest = rest[(places[rest] == places[now]).sum(axis=1) >= SHARED_PLACES]
            for k in rest.tolist():
                if alike(rows[now][3], rows[k][3], similarity):
                    out.append((rows[now][0], rows[k][0]))
                    left[k] = False
                    queue.append(k)
    return out


def verified_edges(nodes: DataFrame, texts: DataFrame, words: int, similarity: float, group_words: int = 4_000_000, group_rows: int = 5_000) -> DataFrame:
    """(u, v): edges that span the groups of nodes whose shingle sets are alike, of (node, size, keys and, for the count filter, fp) and (node, text).

    Lists of one key only say which nodes may be alike: every node of a list is tied to its smallest,
    and the components of these ties hold all pairs to test. Each text goes to its component once, where
    pairs are decided by exact Jaccard before anything is thinned out. A component over ``group_words``
    words or ``group_rows`` rows is dealt out in chunks, and every pair of chunks is tested apart.
    """
    nodes = nodes if "fp" in nodes.columns else nodes.withColumn("fp", F.lit(None).cast("binary"))
    index = nodes.select("node", F.explode("keys").alias("key"))
    heads = index.groupBy("key").agg(F.min("node").alias("head"), F.count("*").alias("n")).where("n > 1").drop("n")
    ties = connected_components(index.join(heads, "key").where("node <> head").select(F.col("node").alias("u"), F.col("head").alias("v")))
    member = ties.join(nodes, "node")
    share = F.greatest(F.sum("size") / group_words, F.count("*") / group_rows)
    member = member.join(member.groupBy("component").agg(F.ceil(share).cast("int").alias("chunks")), "component")
    member = member.withColumn("c", F.pmod(F.xxhash64("node", F.lit(5)), F.greatest("chunks", F.lit(1))).cast("int"))
    member = member.withColumn("o", F.explode(F.sequence(F.lit(0), F.greatest("chunks", F.lit(1)) - 1)))
    dealt = (member.select("component", F.least("c", "o").alias("i"), F.greatest("c", "o").alias("j"), (F.col("c") > F.col("o")).cast("int").alias("side"), "node", "keys", "fp")
             .join(texts, "node").select("component", "i", "j", "side", "node", "keys", "fp", "text")
             .repartition("component", "i", "j").sortWithinPartitions("component", "i", "j", "node"))

    def go(batches):
        at, held = None, []
        for batch in slices(batches):
            edges = []
            for *group, side, node, keys, fp, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if group != at:
                    edges += exact_forest(held, similarity, at[1] != at[2]) if len(held) > 1 else []
                    at, held = group, []
                held.append((node, side, np.array(keys, dtype=np.int64), shingle_set(shingles(text, words)), fp))
            yield pairs(edges)
        if len(held) > 1:
            yield pairs(exact_forest(held, similarity, at[1] != at[2]))

    def pairs(edges):
        return pa.RecordBatch.from_arrays([pa.array([e[k] for e in edges], pa.int64()) for k in (0, 1)], ["u", "v"])

    return dealt.mapInArrow(go, "u long, v long")


def near_duplicate_nodes(rows: DataFrame, row_col: str, words: int, similarity: float, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """((row, doc_id, same), (same, first, least, root)): numbered rows by the digest of their words, and each digest's first row, smallest doc_id and group.

    ``first`` is the struct (doc_id, row) that is smallest among rows with a doc_id; ``root`` tells groups apart, also those of one doc_id.
    """

    def go(batches):
        for batch in slices(batches):
            cols = [[] for _ in range(3)]
            for t in batch.column(2).to_pylist():
                found = (t or "").encode().lower().split()
                hashed = shingle_set(shingles(t, words))
                cols[0].append(xxhash.xxh3_128_digest(b" ".join(found)))
                cols[1].append(len(found))
                cols[2].append(wide_fingerprint(hashed).tobytes())
            kinds = (pa.binary(), pa.int64(), pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))],
                                             ["row", "doc_id", "same", "size", "fp"])

    each = written(rows.select(row_col, F.col(id_col).cast("long").alias("doc_id"), text_col).mapInArrow(
        go, "row long, doc_id long, same binary, size long, fp binary"), "near")
    named = F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "row"))
    nodes = written(each.groupBy("same").agg(F.min("row").alias("node"), F.min(named).alias("first"), F.first("size").alias("size"), F.first("fp").alias("fp")), "near")
    texts = rows.select(F.col(row_col).alias("node"), F.col(text_col).alias("text"))
    sought = nodes.where("first is not null and size > 0").select("node", "size", "fp")
    # groups of close fingerprints only say which texts are compared, so chains of loosely alike texts part again
    close = sought.join(connected_components(wide_edges(sought)), "node").select("node", "size", F.array("component").alias("keys"), "fp")
    groups = connected_components(verified_edges(close, texts, words, similarity))
    found = nodes.join(groups, "node", "left").select("same", "first", F.col("first.doc_id").alias("least"), F.coalesce("component", "node").alias("root"))
    return each.select("row", "doc_id", "same"), written(found, "near")


def numbered(docs: DataFrame, row_col: str) -> DataFrame:
    """The rows, stored with a number each, so that rows of one id or of none can be told apart."""
    return written(docs.select(F.monotonically_increasing_id().alias(row_col), *docs.columns), "rows")


def near_duplicate_groups(docs: DataFrame, words: int = 5, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, component_id): groups of documents linked by shingle sets of at least this Jaccard, each named by its smallest doc_id.

    64-bit fingerprints of five-word shingles differ in ten bits on average at a similarity of 0.8, so
    bytes of them find few such pairs. The search therefore takes SimHash fingerprints of 2,688 bits,
    lists of an inverted index keyed by their byte places and a count of shared places (``wide_edges``),
    and the pairs found are decided by the exact Jaccard of their shingle sets. Equal word sequences (A-Z lowered) are one node before the search. Null or blank texts
    are alike. Rows with a null doc_id have a null group unless others share the text. Repeated rows
    repeat; an empty table gives none.
    """
    rows = numbered(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), "row")
    each, nodes = near_duplicate_nodes(rows, "row", words, similarity, "doc_id", "text")
    names = nodes.groupBy("root").agg(F.min("least").alias("component_id"))
    return each.join(nodes.select("same", "root").join(names, "root"), "same").select("doc_id", "component_id")


def without_near_duplicates(docs: DataFrame, words: int = 5, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each group, the first with its smallest doc_id; columns as given.

    Decided row by row: rows with a null doc_id all stay, and so do unlike texts of one doc_id. The rows
    that stay are found by a minimum over each group and taken by their own number, so that a group with
    a third of all rows is a partial aggregate and never one task's join.
    """
    row_col = free_name(docs, "row_no")
    rows = numbered(docs, row_col)
    _, nodes = near_duplicate_nodes(rows, row_col, words, similarity, id_col, text_col)
    keep = nodes.where("first is not null").groupBy("root").agg(F.min("first")["row"].alias(row_col)).select(row_col)
    return rows.join(keep, row_col, "left_semi").unionByName(rows.where(F.col(id_col).isNull())).select(*docs.columns)
