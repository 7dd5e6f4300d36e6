"""N-gram Jaccard join with signature trees.

1. A text becomes the set of hashes of its word shingles.  Texts with equal sets collapse to the least doc_id.
2. Blocks.  Similar sets must share a key; what shared keys connect is a block, and no link crosses blocks.
   Both kinds of key are exact, whatever the frequency of a shingle.
   From 0.85 on: sets that are similar differ in at most d = floor(a * (den - num) / num) elements, a the smaller size.
   The hash space is cut into d + 1 ranges or more, so on one range the two sets agree wholly; the key is a hash
   of a range's content and the size class.  Below 0.85 ranges hold too few elements to tell sets apart:
   all shingles get one total order, first those not known to be common by hash, then the common ones from rare to frequent, and
   similar sets share one of their first n - ceil(n * num / den) + 1 elements, which are the keys.  Common shingles are
   heavy hitters: tasks keep the most frequent ones of theirs, the sums over all tasks give the COMMON most frequent of the table.
   There a signature tree over the bitmaps and sizes of each key's documents leaves only the links that are possible.
   Where a key's documents are chained anyway, tasks chain their own first and send one row a key.
   Equal sets give one row for each slice of texts.
3. A signature tree over each block: nodes hold the OR of the bitmaps of their sets, the range of sizes and
   the most elements a set has beyond its bits.  A dual traversal drops node pairs whose possible overlap is below
   what the similarity needs, and node pairs already in one component; what is left is compared exactly.
4. A block larger than `block` sets is cut into chunks.  Each chunk is joined with itself and with the block's
   first document; the documents not connected to that one are then a query set against all chunks, in chunks of
   their own.  So a task never holds more than two chunks, and no link is lost.

Defined cases: null or empty text, or text without words, has an empty set and no links; fewer words than a shingle
make one shingle; rows with one doc_id are rows of their own, each with the component of its own text (its label is the least doc_id there);
a null doc_id has component null unless its set equals another's; an empty table gives no rows; other columns are ignored or kept."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from innersearch.llm.common import annotate, bound_batches, columns_of, components, fresh, materialize, small_side, text_slices, tidy

WORDS, NUM, DEN = 3, 90, 100
BLOCK = 1024
#: Similarities from this one on use range keys, smaller ones prefix keys (both are exact).
RANGES_FROM = (85, 100)
#: Most ids of one key that a task holds.
RUN = 4096
#: Most shingles that are known as common (16 bytes each, broadcast), and most that a task counts at a time.
COMMON = 2**18
TASK_COMMON = 2**17
#: Key rows that a task chains at a time before it sends them.
FLUSH = 2**19
LEAF, FAN = 16, 4

_FOLD = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_IS_WORD = np.array([not (b == 32 or 9 <= b <= 13) for b in range(256)])
_RNG = np.random.default_rng(97)
_BYTE = _RNG.integers(0, 2**64, 256, np.uint64, endpoint=False)
_PLACE = _RNG.integers(0, 2**64, 4096, np.uint64, endpoint=False) | np.uint64(1)
_MULT = _RNG.integers(0, 2**64, 64, np.uint64, endpoint=False) | np.uint64(1)


def mixed(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A 64-bit finalizer (multiply and shift rounds)."""
    x = x + np.uint64((0x9E3779B97F4A7C15 * (salt + 1)) % 2**64)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_sets(texts: list[bytes | None], words: int = WORDS) -> list[np.ndarray]:
    """The sorted shingle hashes of each text, all texts hashed together."""
    folded = [(t or b"").translate(_FOLD) for t in texts]
    data = np.frombuffer(b"\n".join([*folded, b""]), np.uint8)
    if not len(data):
        return [np.zeros(0, np.uint64) for _ in texts]
    is_word = _IS_WORD[data]
    flags = np.diff(np.concatenate([[0], is_word.view(np.int8), [0]]))
    begins, ends = np.flatnonzero(flags == 1), np.flatnonzero(flags == -1)
    if not len(begins):
        return [np.zeros(0, np.uint64) for _ in texts]
    lens = ends - begins
    first = np.cumsum(lens) - lens
    place = np.arange(int(lens.sum())) - np.repeat(first, lens)
    value = _BYTE[data[is_word]] * _PLACE[place & 4095]
    if int(lens.max()) > 4096:
        value *= _PLACE[(place >> 12) & 4095]
    h = mixed(np.add.reduceat(value, first) + lens.astype(np.uint64))
    offsets = np.cumsum([0, *[len(t) + 1 for t in folded]])
    cut = np.searchsorted(begins, offsets)
    rolled = np.zeros(max(0, len(h) - words + 1), np.uint64)
    for k in range(words):
        rolled += h[k : k + len(rolled)] * _MULT[k]
    rolled = mixed(rolled, words)
    out = []
    for i in range(len(texts)):
        a, b = int(cut[i]), int(cut[i + 1])
        if b - a >= words:
            out.append(np.unique(rolled[a : b - words + 1]))
        elif b > a:
            out.append(mixed((h[a:b] * _MULT[8 : 8 + b - a]).sum(keepdims=True, dtype=np.uint64), b - a))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def size_classes(num: int, den: int, most: int = 2**40) -> list[int]:
    """Lower bounds of the size classes; sets below the first differ in nothing if they are similar."""
    low = [-(-num // (den - num)) if den > num else most]
    while low[-1] < most:
        low.append(max(low[-1] + 1, low[-1] * 3 // 2, -(-low[-1] * den // num)))
    return low


def range_keys(s: np.ndarray, classes: list[int], num: int, den: int) -> np.ndarray:
    """Keys of a sorted set in its own size class and, if a smaller partner may be there, in the class below."""
    n = len(s)
    if n < classes[0]:
        return np.zeros(0, np.int64)
    own = int(np.searchsorted(classes, n, "right")) - 1
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mixed(s, 7))])
    out = []
    for c in (own, own - 1):
        if c < 0 or (c < own and (classes[c + 1] - 1) * den < n * num):
            continue
        most = classes[c + 1] - 1
        ranges = most * (den - num) // num + 1
        step = (2**64 - 1) // ranges + 1
        at = np.concatenate([[0], np.searchsorted(s, np.arange(1, ranges, dtype=np.uint64) * np.uint64(step % 2**64)), [n]]) if ranges > 1 else np.array([0, n])
        content, full = total[at[1:]] - total[at[:-1]], at[1:] > at[:-1]
        keys = mixed(content ^ mixed(np.arange(ranges, dtype=np.uint64), 1000 + c), 3).view(np.int64)
        # as many full ranges as there can be differences, and one more, or empty ranges count too
        out.append(keys[full] if int(full.sum()) > min(n, most) * (den - num) // num else keys)
    return np.unique(np.concatenate(out))


def least_linkable(num: int, den: int) -> int:
    """Sets smaller than this link with equal sets only."""
    return -(-num // (den - num)) if den > num else 2**62


class Order:
    """The total order of shingles: those not common by hash, then the common ones by count.  Common ones with over RUN
    sets are hot."""

    def __init__(self, hashes: np.ndarray, counts: np.ndarray):
        at = np.argsort(hashes)
        self.hashes, counts = hashes[at], counts[at]
        self.rank = np.empty(len(at), np.int64)
        self.rank[np.lexsort((self.hashes, counts))] = np.arange(len(at))
        self.hot = self.hashes[counts > RUN].view(np.int64)

    def prefix(self, s: np.ndarray, num: int, den: int) -> np.ndarray:
        """The first elements of a sorted set, as keys."""
        p = len(s) - -(-len(s) * num // den) + 1
        if len(self.hashes):
            at = np.minimum(np.searchsorted(self.hashes, s), len(self.hashes) - 1)
            common = self.hashes[at] == s
            rare = s[~common]
            if len(rare) < p:
                known = at[common]
                s = np.concatenate([rare, self.hashes[known[np.argsort(self.rank[known])]]])
            else:
                s = rare
        return s[:p].view(np.int64)


def _merged(keys: np.ndarray, counts: np.ndarray, more: list[np.ndarray], most: int) -> tuple[np.ndarray, np.ndarray]:
    """Counts of keys with those of further hashes; beyond `most` keys all counts lose what the first key left out has
    (a frequent-items summary: a key found more often than all hashes / `most` stays)."""
    k, n = np.unique(np.concatenate(more), return_counts=True)
    every, at = np.unique(np.concatenate([keys, k]), return_inverse=True)
    total = np.bincount(at, np.concatenate([counts, n]), len(every)).astype(np.int64)
    if len(every) > most:
        total -= np.partition(total, len(total) - most - 1)[len(total) - most - 1]
        every, total = every[total > 0], total[total > 0]
    return every, total


def common_shingles(docs: DataFrame, words: int) -> Order:
    """The order by the most frequent shingles of docs.

    A task sends at most TASK_COMMON rows (those found twice or more), and at most COMMON reach the driver: all
    whose count is in the upper classes, four to each power of two, that COMMON holds whole."""

    def run(batches):
        import pyarrow as pa

        keys, counts, held, n = np.zeros(0, np.uint64), np.zeros(0, np.int64), [], 0
        for batch in batches:
            texts = batch.column(0).cast(pa.large_binary())
            for at, end in text_slices(texts):
                sets = shingle_sets(texts[at:end].to_pylist(), words)
                held += sets
                n += sum(len(s) for s in sets)
                if n >= 8 * TASK_COMMON:
                    keys, counts = _merged(keys, counts, held, TASK_COMMON)
                    held, n = [], 0
        if held:
            keys, counts = _merged(keys, counts, held, TASK_COMMON)
        often = counts > 1
        yield pa.RecordBatch.from_arrays([pa.array(keys[often].view(np.int64)), pa.array(counts[often])], names=["h", "n"])

    found = docs.select("text").mapInArrow(tidy(run), "h long, n long").groupBy("h").agg(F.sum("n").alias("n"))
    found = materialize(found.withColumn("class", F.floor(4 * F.log2("n")).cast("int")), "common_shingles")
    held, least = 0, 2**31 - 1
    for r in sorted(found.groupBy("class").agg(F.count("*").alias("rows")).collect(), reverse=True):
        held += r["rows"]
        if held > COMMON:
            break
        least = r["class"]
    got = found.where(F.col("class") >= least).select("h", "n").toPandas()
    return Order(got["h"].to_numpy(np.int64).view(np.uint64), got["n"].to_numpy(np.int64))


def _prints(s: np.ndarray) -> tuple[int, int, int]:
    """Two fingerprints of a set, and the node id made of them (not 0; collisions only add candidates)."""
    f1, f2 = (mixed(s, salt).sum(dtype=np.uint64) for salt in (21, 22))
    node = mixed(np.array([f1], np.uint64) ^ mixed(np.array([f2], np.uint64), len(s) & 0xFFFF), 23)[0]
    return int(f1.astype(np.int64)), int(f2.astype(np.int64)), int(node.astype(np.int64)) or 1


def set_table(docs: DataFrame, words: int) -> DataFrame:
    """doc_id, th, n, fingerprint (f1, f2), node id and bitmap of every row."""

    def make():
        def work(texts):
            sets = shingle_sets(texts, words)
            prints = [_prints(s) for s in sets]
            return [[len(s) for s in sets], *[list(c) for c in zip(*prints, strict=True)], [bitmap(s).tobytes() for s in sets]]

        return work

    return annotate(docs, ["doc_id", "th"], "n long, f1 long, f2 long, node long, bits binary", make)


def _sent(keys: list[np.ndarray], ids: list[int], hot: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows (key, id, to) of sets: with `to` 0 the key is the id's; else id and to are chained.

    Keys in `hot` (None: all) send one id, the least, which is chained with the others."""
    v = np.repeat(np.array(ids, np.int64), [len(k) for k in keys])
    k = np.concatenate(keys)
    at = np.lexsort((v, k))
    k, v = k[at], v[at]
    new = np.concatenate([[True], k[1:] != k[:-1]])
    head = v[np.maximum.accumulate(np.where(new, np.arange(len(k)), 0))]
    tied = np.ones(len(k), bool) if hot is None else np.isin(k, hot)
    own, other = new | ~tied, tied & ~new & (head != v)
    pairs = np.unique(np.stack([head[other], v[other]], 1), axis=0)
    any_key = mixed(pairs[:, 0].view(np.uint64) ^ mixed(np.ascontiguousarray(pairs[:, 1]).view(np.uint64), 51)).view(np.int64) if len(pairs) else np.zeros(0, np.int64)
    return np.concatenate([k[own], any_key]), np.concatenate([v[own], pairs[:, 0]]), np.concatenate([np.zeros(int(own.sum()), np.int64), pairs[:, 1]])


def key_table(docs: DataFrame, words: int, num: int, den: int, ranges: bool) -> DataFrame:
    """Rows (key, id, to) of the range or prefix keys of every set, id its node (see _sent).

    Equal sets of a slice of texts give one row for each key; so do, of a hot key, all sets that a task holds at a time."""
    shared = None if ranges else docs.sparkSession.sparkContext.broadcast(common_shingles(docs, words))
    classes = size_classes(num, den) if ranges else []
    least = least_linkable(num, den)

    def run(batches):
        import pyarrow as pa

        def out():
            return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(x)) for x in _sent(list(made.values()), list(made), None if ranges else shared.value.hot)], names=["key", "id", "to"])

        made: dict[int, np.ndarray] = {}
        n = 0
        for batch in batches:
            texts = batch.column(0).cast(pa.large_binary())
            for at, end in text_slices(texts):
                for s in shingle_sets(texts[at:end].to_pylist(), words):
                    if len(s) >= least:
                        node = _prints(s)[2]
                        if node not in made:
                            made[node] = (range_keys(s, classes, num, den) if ranges else shared.value.prefix(s, num, den)).copy()
                            n += len(made[node])
                if n >= FLUSH:
                    yield out()
                    made, n = {}, 0
        if made:
            yield out()

    return docs.select("text").mapInArrow(tidy(run), "key long, id long, to long")


def chained(keys: DataFrame) -> DataFrame:
    """Distinct pairs (a, b) of the least id and each other id of the rows (key, id, to) with one key, and the pairs (id, to).

    One shuffle by key; a task streams its sorted rows."""

    def run(batches):
        import pyarrow as pa

        last_key = least = None
        for batch in batches:
            k, v, to = (batch.column(i).to_numpy() for i in range(3))
            sure = np.stack([v, to], 1)[to != 0]
            k, v = k[to == 0], v[to == 0]
            if len(k):
                new = np.concatenate([[last_key is None or k[0] != last_key], k[1:] != k[:-1]])
                heads = np.where(new, v, 0)
                if not new[0]:
                    heads[0] = least
                at = np.maximum.accumulate(np.where(new, np.arange(len(k)), 0))
                head = heads[at]
                last_key, least = k[-1], head[-1]
                other = head != v
                sure = np.concatenate([sure, np.stack([head[other], v[other]], 1)])
            pairs = np.unique(sure, axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0].copy()), pa.array(pairs[:, 1].copy())], names=["a", "b"])

    return keys.repartition("key").sortWithinPartitions("key", "id").mapInArrow(tidy(run), "a long, b long").distinct()


def key_groups(keys: DataFrame) -> DataFrame:
    """Distinct rows (grp, id, chained) of the ids that share a key: groups with the same ids are one group.

    One shuffle by key; a task streams its sorted rows and holds one run of equal keys, up to RUN ids.  A longer run
    becomes chained pairs, the least id with each other one, which all count as possible links, as do the pairs (id, to)."""

    def run(batches):
        import pyarrow as pa

        def rows(k: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            """Groups of whole runs: equal (key, id) rows once, runs of one id dropped."""
            once = np.concatenate([[True], (k[1:] != k[:-1]) | (v[1:] != v[:-1])])
            k, v = k[once], v[once]
            start = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
            n = np.diff(np.append(start, len(k)))
            name = np.repeat(np.add.reduceat(mixed(v.view(np.uint64), 41), start).view(np.int64), n)
            many = np.repeat(n > 1, n)
            return name[many], v[many]

        def batch_of(g: np.ndarray, v: np.ndarray, chained: bool = False):
            pairs = np.unique(np.stack([g, v], 1), axis=0) if len(g) else np.zeros((0, 2), np.int64)
            return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1]), pa.array(np.full(len(pairs), chained))], names=["grp", "id", "chained"])

        def chain(least: int | np.ndarray, v: np.ndarray):
            pairs = np.stack(np.broadcast_arrays(least, v), 1)
            pairs = np.unique(pairs[pairs[:, 0] != pairs[:, 1]], axis=0)
            g = mixed(np.ascontiguousarray(pairs).view(np.uint64), 41).sum(1, dtype=np.uint64).view(np.int64)
            return batch_of(np.repeat(g, 2), pairs.ravel(), True)

        k, v, hot = np.zeros(0, np.int64), np.zeros(0, np.int64), None
        for batch in batches:
            if not batch.num_rows:
                continue
            key, id_, to = (batch.column(i).to_numpy() for i in range(3))
            own = to == 0
            if not own.all():
                yield chain(id_[~own], to[~own])
            k, v = np.concatenate([k, key[own]]), np.concatenate([v, id_[own]])
            if hot is not None:
                n = int(np.searchsorted(k, hot[0], "right"))
                if n:
                    yield chain(hot[1], v[:n])
                    k, v = k[n:], v[n:]
                hot = hot if not len(k) else None
            if not len(k):
                continue
            cut = int(np.searchsorted(k, k[-1]))  # the last run may go on
            if cut:
                yield batch_of(*rows(k[:cut], v[:cut]))
                k, v = k[cut:], v[cut:]
            if len(k) > RUN:
                hot = (k[0], int(v[0]))
                yield chain(hot[1], v)
                k, v = k[:0], v[:0]
        if len(k):
            yield batch_of(*rows(k, v))

    return keys.repartition("key").sortWithinPartitions("key", "id").mapInArrow(tidy(run), "grp long, id long, chained boolean").distinct()


def possible_links(groups: DataFrame, maps: DataFrame, num: int, den: int) -> DataFrame:
    """Pairs (a, b) of ids that chain, in each group, what its bitmaps and sizes leave possible.

    A signature tree over the group's bitmaps with a dual traversal; a worker holds one group."""

    def run(batches):
        import pyarrow as pa

        now, held, out = None, [], []
        for batch in batches:
            for g, i, n, m in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                if g != now:
                    out += _possible(held, num, den)
                    now, held = g, []
                held.append((i, n, m))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in out]), pa.array([p[1] for p in out])], names=["a", "b"])
                out = []
        out = _possible(held, num, den)
        if out:
            yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in out]), pa.array([p[1] for p in out])], names=["a", "b"])

    met = maps.join(small_side(groups.where("not chained").select("grp", "id")), F.col("node") == F.col("id")).select("grp", "id", "n", "bits")
    found = met.repartition("grp").sortWithinPartitions("grp", "n").mapInArrow(tidy(run), "a long, b long")
    pairs = groups.where("chained").groupBy("grp").agg(F.min("id").alias("a"), F.max("id").alias("b")).select("a", "b")
    return found.unionByName(pairs).distinct()


def _possible(held: list[tuple[int, int, bytes]], num: int, den: int) -> list[tuple[int, int]]:
    """A forest of the pairs that bitmaps and sizes of (id, size, bitmap) leave possible.

    Bitmaps of one width make one tree; a tree of wider ones is folded only to meet the narrower one, and only with
    the sets whose size allows that."""
    by: dict[int, list] = {}
    for i, n, m in held:
        by.setdefault(len(m) // 8, []).append((i, n, np.frombuffer(m, np.uint64)))

    def tree(some: list, width: int) -> Block:
        maps = np.stack([m.reshape(-1, width) for _, _, m in some])
        return Block([i for i, _, _ in some], None, num, den, np.array([n for _, n, _ in some], np.int64), np.bitwise_or.reduce(maps, 1))

    out = []
    for width, some in by.items():
        if len(held) == len(some) == 1:
            return []
        own = tree(some, width)
        own.join_self()
        out += own.forest()
        most = int(own.n.max()) * den
        for wider in by:
            met = [x for x in by[wider] if x[1] * num <= most] if wider > width else []
            if met:
                out += own.links_with(tree(met, width))
    return out


def bitmap(s: np.ndarray, spare: int = 2) -> np.ndarray:
    """From 2^spare to twice as many bits an element, a power of two from 256 to 2^15, at the low bits of the hashes: a larger
    map folds to a smaller one by OR of its halves."""
    bits = 1 << int(min(15, max(8, len(s).bit_length() + spare)))
    at = (s & np.uint64(bits - 1)).astype(np.int64)
    flags = np.zeros(bits, np.uint8)
    flags[at] = 1
    return np.packbits(flags, bitorder="little").view(np.uint64)


class Block:
    """A signature tree over sets, and the components found by a dual traversal."""

    def __init__(self, ids: list[int], sets: list[np.ndarray] | None, num: int, den: int, n: np.ndarray | None = None, maps: np.ndarray | None = None):
        self.num, self.den = num, den
        if maps is None:
            order = sorted(range(len(ids)), key=lambda i: (int(sets[i][0]), len(sets[i]), ids[i]))
            self.ids, self.sets = [ids[i] for i in order], [sets[i] for i in order]
            self.n = np.array([len(s) for s in self.sets], np.int64)
            wide = [bitmap(s) for s in self.sets]
            most = max(len(m) for m in wide)
            self.maps = np.stack([m if len(m) == most else self._widened(s, most) for m, s in zip(wide, self.sets, strict=True)])
        else:
            self.ids, self.sets, self.n, self.maps = ids, None, n, maps
        self.extra = self.n - np.bitwise_count(self.maps).sum(1, dtype=np.int64)
        number = {x: i for i, x in enumerate(dict.fromkeys(self.ids))}
        self.label = np.array([number[x] for x in self.ids], np.int64)
        self.levels = self._build()

    @staticmethod
    def _widened(s: np.ndarray, words: int) -> np.ndarray:
        flags = np.zeros(words * 64, np.uint8)
        flags[(s & np.uint64(words * 64 - 1)).astype(np.int64)] = 1
        return np.packbits(flags, bitorder="little").view(np.uint64)

    def _build(self) -> list[tuple]:
        """Levels of nodes from the leaves up: OR maps, least size, greatest size, extra, first and last set."""
        first = np.arange(0, len(self.n), LEAF)
        nodes = (np.bitwise_or.reduceat(self.maps, first, 0), np.minimum.reduceat(self.n, first), np.maximum.reduceat(self.n, first), np.maximum.reduceat(self.extra, first), first, np.append(first[1:], len(self.n)))
        levels = [nodes]
        while len(levels[-1][1]) > 1:
            m, lo, hi, ex, b, e = levels[-1]
            at = np.arange(0, len(lo), FAN)
            levels.append((np.bitwise_or.reduceat(m, at, 0), np.minimum.reduceat(lo, at), np.maximum.reduceat(hi, at), np.maximum.reduceat(ex, at), b[at], e[np.append(at[1:], len(lo)) - 1]))
        return levels

    def _may(self, la: int, a: int, other: Block, lb: int, b: int) -> bool:
        """Can sets of the two nodes overlap enough?"""
        ma, loa, hia, xa, *_ = (x[a] for x in self.levels[la])
        mb, lob, hib, xb, *_ = (x[b] for x in other.levels[lb])
        need = self.num * (loa + lob)
        scale = self.num + self.den
        if min(hia, hib) * scale < need or hia * self.den < lob * self.num or hib * self.den < loa * self.num:
            return False
        if ma.shape != mb.shape:
            return True
        common = int(np.bitwise_count(ma & mb).sum())
        return (common + min(xa, xb)) * scale >= need

    def _alike(self, s: np.ndarray, t: np.ndarray) -> bool:
        if len(s) > len(t):
            s, t = t, s
        if len(s) * self.den < len(t) * self.num:
            return False
        at = np.searchsorted(t, s)
        at[at == len(t)] = 0
        both = int((t[at] == s).sum())
        return self.den * both >= self.num * (len(s) + len(t) - both)

    def join_self(self) -> None:
        """Merges the labels of all linked sets."""
        stack = [(len(self.levels) - 1, 0, 0)]
        while stack:
            level, a, b = stack.pop()
            nodes = self.levels[level]
            (ba, ea), (bb, eb) = (nodes[4][a], nodes[5][a]), (nodes[4][b], nodes[5][b])
            first = self.label[ba]
            if (self.label[ba:ea] == first).all() and (self.label[bb:eb] == first).all():
                continue
            if a != b and not self._may(level, a, self, level, b):
                continue
            if level:
                below = len(self.levels[level - 1][1])
                ca, cb = (range(x * FAN, min(x * FAN + FAN, below)) for x in (a, b))
                pairs = [(level - 1, i, j) for i in ca for j in cb if a != b or i < j]
                stack += pairs if a != b else [*pairs, *[(level - 1, i, i) for i in ca]]
                continue
            for i in range(ba, ea):
                for j in range(i + 1 if a == b else bb, eb):
                    if self.label[i] != self.label[j] and self._pair(i, self, j):
                        self.label[self.label == self.label[j]] = self.label[i]

    def _pair(self, i: int, other: Block, j: int) -> bool:
        if self.maps.shape[1] == other.maps.shape[1]:
            common = int(np.bitwise_count(self.maps[i] & other.maps[j]).sum()) + min(self.extra[i], other.extra[j])
            if common * (self.num + self.den) < self.num * (self.n[i] + other.n[j]):
                return False
        if self.sets is None:  # bitmaps alone: possible
            small, large = sorted((int(self.n[i]), int(other.n[j])))
            return small * self.den >= large * self.num
        return self._alike(self.sets[i], other.sets[j])

    def links_with(self, other: Block) -> list[tuple[int, int]]:
        """Links (own id, other id); sets of self already tied to a label of other are not compared again."""
        out, tied = [], set()
        stack = [(len(self.levels) - 1, 0, len(other.levels) - 1, 0)]
        while stack:
            la, a, lb, b = stack.pop()
            if not self._may(la, a, other, lb, b):
                continue
            if la and la >= lb:
                stack += [(la - 1, i, lb, b) for i in range(a * FAN, min(a * FAN + FAN, len(self.levels[la - 1][1])))]
            elif lb:
                stack += [(la, a, lb - 1, j) for j in range(b * FAN, min(b * FAN + FAN, len(other.levels[lb - 1][1])))]
            else:
                for i in range(self.levels[0][4][a], self.levels[0][5][a]):
                    for j in range(other.levels[0][4][b], other.levels[0][5][b]):
                        key = (int(self.label[i]), int(other.label[j]))
                        if key not in tied and self._pair(i, other, j):
                            tied.add(key)
                            out.append((self.ids[i], other.ids[j]))
        return out

    def forest(self) -> list[tuple[int, int]]:
        """(id, least id of its component) for every set not the least itself."""
        least: dict[int, int] = {}
        for x, y in zip(self.ids, self.label.tolist(), strict=True):
            least[y] = min(x, least.get(y, x))
        return sorted({(x, least[y]) for x, y in zip(self.ids, self.label.tolist(), strict=True) if least[y] != x})


def joined_tasks(rows: DataFrame, words: int, num: int, den: int) -> DataFrame:
    """Links (a, b) of nodes (id, f), as a spanning forest, of rows (task, side, node, text) with one task.

    Side 0 is joined with itself if there is no side 1, else with side 1.  A worker holds one task's sets.  A text that
    does not have the fingerprint f of its node belongs to another row of the doc_id and is left out."""

    def run(batches):
        import pyarrow as pa

        def solve(held):
            sides = []
            for side in (0, 1):
                some = {i: sig for s, i, sig in held if s == side and len(sig)}
                sides.append(Block(list(some), list(some.values()), num, den) if some else None)
            if sides[0] is None:
                return []
            if sides[1] is None:
                sides[0].join_self()
                return sides[0].forest()
            for b in sides:
                b.join_self()
            return [p for p in sides[0].links_with(sides[1]) if p[0] != p[1]]

        def out(pairs):
            return pa.RecordBatch.from_arrays([pa.array([p[k][j] for p in pairs], pa.int64()) for k in (0, 1) for j in (0, 1)], names=["ai", "af", "bi", "bf"])

        now, held = None, []
        for batch in batches:
            pairs = []
            texts = batch.column(4).cast(pa.large_binary())
            for at, end in text_slices(texts):
                m = end - at
                sets = shingle_sets(texts.slice(at, m).to_pylist(), words)
                for task, side, i, f, sig in zip(*[batch.column(c).slice(at, m).to_pylist() for c in range(4)], sets, strict=True):
                    if task != now:
                        pairs += solve(held)
                        now, held = task, []
                    if _prints(sig)[0] == f:
                        held.append((side, (i, f), sig.copy()))
            if pairs:
                yield out(pairs)
        pairs = solve(held)
        if pairs:
            yield out(pairs)

    flat = rows.select("task", "side", "node.id", "node.f", "text")
    found = flat.repartition("task").sortWithinPartitions("task", "side", "id", "f").mapInArrow(tidy(run), "ai long, af long, bi long, bf long")
    return found.select(F.struct(F.col("ai").alias("id"), F.col("af").alias("f")).alias("a"), F.struct(F.col("bi").alias("id"), F.col("bf").alias("f")).alias("b"))


def similar_components(docs: DataFrame, words: int = WORDS, num: int = NUM, den: int = DEN, block: int = BLOCK) -> DataFrame:
    """doc_id, n_shingles, component_id of every row of docs(doc_id, text)."""
    return row_components(docs, words, num, den, block).drop("th")


def row_components(docs: DataFrame, words: int = WORDS, num: int = NUM, den: int = DEN, block: int = BLOCK) -> DataFrame:
    """similar_components with th, the xxhash64 of the text.

    A set is known by its node: the least doc_id of its rows and a fingerprint, for one doc_id may have several sets."""
    bound_batches(docs.sparkSession)
    narrow = docs.select("doc_id", "text", F.xxhash64("text").alias("th"))
    sets = materialize(set_table(narrow, words), "sets")
    groups = sets.where("n > 0").groupBy("n", "f1", "f2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies"), F.min("node").alias("g_node"), F.first("bits").alias("bits"))
    groups = materialize(groups, "set_groups")
    node_of = lambda i: F.struct(F.col(i).alias("id"), F.col("f1").alias("f"))
    reps = groups.where("rep is not null").select(node_of("rep").alias("set_node"), "g_node")
    ranges = num * RANGES_FROM[1] >= den * RANGES_FROM[0]
    # a set without a rep must not be the least id of a key, or the other ids of the key are tied to nothing
    keys = key_table(narrow.where("doc_id is not null"), words, num, den, ranges)
    if ranges:
        edges = chained(keys)
    else:
        maps = groups.where("rep is not null").select(F.col("g_node").alias("node"), "n", "bits")
        edges = possible_links(materialize(key_groups(keys), "key_groups"), maps, num, den)
    edges = materialize(edges, "possible")
    edges = edges.join(reps.toDF("ra", "na"), F.col("a") == F.col("na")).join(reps.toDF("rb", "nb"), F.col("b") == F.col("nb")).select(F.col("ra").alias("a"), F.col("rb").alias("b"))
    parts = materialize(components(edges), "blocks").withColumnRenamed("label", "part")
    sizes = parts.groupBy("part").agg(F.count("*").alias("members"))
    members = parts.join(sizes.where(F.col("members") > block), "part", "left").select("node", "part", F.coalesce("members", F.lit(0)).alias("members"))
    small = members.where("members = 0").select("node", "part")
    texts = narrow.select(F.col("doc_id").alias("t_id"), "text")

    def tasks(rows: DataFrame, task) -> DataFrame:
        asked = small_side(rows.select(task.alias("task"), "side", "node"))
        return texts.join(asked, F.col("node.id") == F.col("t_id")).select("task", "side", "node", "text")

    links = joined_tasks(tasks(small.withColumn("side", F.lit(0)), F.struct("part", F.lit(0).alias("x"), F.lit(0).alias("y"))), words, num, den)
    links = materialize(links, "links")
    large = members.where("members > 0")
    if not large.isEmpty():
        links = components(links.unionByName(_large_links(large, tasks, words, num, den, block)))
    else:
        links = links.toDF("node", "label")
    final = links.where("node != label").distinct()
    many = groups.where("copies > 1").select("n", "f1", "f2", F.col("rep").alias("of"))
    out = sets.select("doc_id", "th", "n", "f1", "f2").join(many, ["n", "f1", "f2"], "left").withColumn("of", F.coalesce("of", "doc_id"))
    out = out.join(final, node_of("of") == F.col("node"), "left")
    return out.select("doc_id", "th", F.col("n").alias("n_shingles"), F.coalesce("label.id", "of").alias("component_id"))


def _large_links(large: DataFrame, tasks, words: int, num: int, den: int, block: int) -> DataFrame:
    """Links of the blocks with more than `block` sets, chunk by chunk."""
    chunks = F.ceil(F.col("members") / (block // 2)).cast("int")
    large = materialize(large.withColumn("chunks", chunks).withColumn("chunk", F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int")), "large")
    zero = F.lit(0)
    centre = large.where("node = part").withColumn("chunk", F.explode(F.sequence(zero, F.col("chunks") - 1)))
    first = large.unionByName(centre).distinct().withColumn("side", zero)
    found = materialize(joined_tasks(tasks(first, F.struct("part", F.col("chunk").alias("x"), zero.alias("y"))), words, num, den), "chunk_links")
    tied = components(found).withColumnRenamed("node", "t_node")
    open_ = large.join(tied, F.col("node") == F.col("t_node"), "left").where(F.coalesce("label", "node") != F.col("part")).select("node", "part", "members", "chunks", "chunk")
    open_ = materialize(open_, "open")
    if open_.isEmpty():
        return found
    per = open_.groupBy("part").agg(F.count("*").alias("n_open")).select("part", F.ceil(F.col("n_open") / (block // 2)).cast("int").alias("ys"))
    asked = open_.join(per, "part").withColumn("y", F.pmod(F.xxhash64("node", F.lit(1)), F.col("ys")).cast("int")).withColumn("x", F.explode(F.sequence(zero, F.col("chunks") - 1)))
    held = large.join(per, "part").withColumn("x", F.col("chunk")).withColumn("y", F.explode(F.sequence(zero, F.col("ys") - 1)))
    both = held.select("node", "part", "x", "y", zero.alias("side")).unionByName(asked.select("node", "part", "x", "y", F.lit(1).alias("side")))
    more = joined_tasks(tasks(both, F.struct("part", "x", (F.col("y") + 1).alias("y"))), words, num, den)
    return found.unionByName(materialize(more, "open_links"))


def keep_one(docs: DataFrame, **options: int) -> DataFrame:
    """docs with one row - the least doc_id - of each component of similar texts.

    Rows without a doc_id stay.  Of rows with one doc_id, each goes or stays by its own text, and one of equal rows stays."""
    found = materialize(row_components(docs, **options), "components").where("doc_id is not null")
    gone, again, th = (fresh(docs.columns, n) for n in ("gone", "again", "th"))
    rows = docs.withColumn(th, F.xxhash64("text"))
    lost = small_side(found.where("doc_id != component_id").select(F.col("doc_id").alias(gone), F.col("th").alias(again)).distinct())
    kept = rows.join(lost, (F.col("doc_id") == F.col(gone)) & (F.col(th) == F.col(again)), "left_anti")
    twice = materialize(found.where("doc_id = component_id").groupBy("doc_id").agg(F.count("*").alias("rows")).where("rows > 1").select(F.col("doc_id").alias(gone)), "repeated")
    if not twice.isEmpty():
        met = F.col("doc_id") == F.col(gone)
        kept = kept.join(small_side(twice), met, "left_anti").unionByName(kept.join(small_side(twice), met, "left_semi").dropDuplicates(["doc_id"]))
    return kept.select(*columns_of(docs))
