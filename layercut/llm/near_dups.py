"""Operator 5: near-duplicates by a chosen-path set similarity join.

Equal sets become one record first. Each tree deals all records to nodes by one minwise token. A node with more than LEAF records
first takes out its central records, which agree with the node's others on DENSE of their coordinates on average: these are compared
with all of the node that is not in their group yet. The others go to one child for each of a few coordinates that the node's name
chooses, by their token there. Small nodes are compared exhaustively, and TREES independent trees raise recall: two records of
similarity 0.85 part in every tree with a chance below 1e-6 however deep the trees go (0.85 * (1 - 0.15^5) * (1 - 0.15^3)^5 is
the chance to meet in one).

Whole trees of a node run in one task up to NODE records. Larger nodes are dealt out: their central records in chunks that all hold the
node's HEADS, then those outside the largest group against all others, chunk by chunk; the rest branches on in Spark. Nothing is
capped, and nodes take the same children on either path.

Nodes compare sketches only, which rules out pairs far below the threshold (estimates below FAR). What remains connected is one
candidate group, and as candidate groups share no records, each full set is read and moved once; a group's links are then exact.
Inside a group a member meets only those that it is not connected with yet, through the postings of its rarest shingles where that is less work.

Defined results: null, empty and word-less texts have an empty set and link to nothing; texts of one or two words are one shingle;
repeated rows are copies; rows that repeat a doc_id with another text are records of their own; rows without an id link like all others, take
the name of their component (null if it has none) and are never `kept`; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import HOT_SHARE, cut_lineage, join_spread, small_or_shuffled, table
from .rolling import KEPT, span_hashes, stir

#: Percent of similarity; words of a shingle; coordinates of a sketch; trees; records of a node compared exhaustively.
PERCENT, SHINGLE, SKETCH, TREES, LEAF = 85, 3, 64, 8, 256
#: Estimates below this rule a pair out: 6 standard deviations below the threshold.
FAR = 0.58
#: Children that a record gets on the first and on later levels; levels; average agreement of central records.
FIRST, NEXT, DEPTH, DENSE = 5, 3, 6, 0.5
#: Records of a node, and shingles of a candidate group, that one task takes; members that all chunks of a larger one hold.
NODE, GROUP_SHINGLES, HEADS = 8192, 1 << 19, 8
#: Texts hashed at a time; edges of an id from which on it counts as a hub (and more than HOT_SHARE of all edges).
TEXTS, HUB = 256, 1000
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)


_WHITE = np.isin(np.arange(256), [0x20, *range(0x09, 0x0E)])


def word_hashes(buf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash, start) of the words of buf, """
    word = np.append(~_WHITE[buf], False)
    edge = np.flatnonzero(word != np.append(False, word[:-1]))
    start, stop = edge[::2], edge[1::2]
    return span_hashes(buf, start, stop), start


def shingle_sets(texts: list[str | None], size: int = SHINGLE) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes of each text."""
    raw = [(t or "").encode("utf-8", "surrogatepass").translate(_LOWER) for t in texts]
    out: list[np.ndarray] = []
    a = 0
    while a < len(raw):
        b, held = a + 1, len(raw[a]) + 1
        while b < len(raw) and held + len(raw[b]) < KEPT - 1:
            b, held = b + 1, held + len(raw[b]) + 1
        h, start = word_hashes(np.frombuffer(b" ".join(raw[a:b]), dtype=np.uint8))
        begin = np.append(0, np.cumsum([len(r) + 1 for r in raw[a:b]]))
        cut = np.searchsorted(start, begin)  # words before each text
        n = np.zeros(len(h), dtype=np.uint64)
        full = np.diff(cut)
        n[:] = np.repeat(np.minimum(full, size), full)
        mixed = np.zeros(len(h), dtype=np.uint64)
        for k in range(min(size, len(h))):
            stirred = stir(mixed[: len(h) - k] * _MIX[2] + h[k:] * _MIX[k % 2] + np.uint64(k + 1))
            mixed[: len(h) - k] = np.where(n[: len(h) - k] > k, stirred, mixed[: len(h) - k])
        mixed += n
        out += [np.unique(mixed[i : max(i, j - min(size, j - i) + 1)]) if j > i else np.empty(0, dtype=np.uint64) for i, j in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)]
        a = b
    return out


def _sets_of(texts: pd.Series) -> Iterator[np.ndarray]:
    for a in range(0, len(texts), TEXTS):
        yield from shingle_sets(texts.iloc[a : a + TEXTS].tolist())


def _multipliers(count: int = SKETCH) -> np.ndarray:
    return np.random.default_rng(5).integers(1, 2**63, size=count, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def minwise_tokens(members: np.ndarray, by: np.ndarray) -> np.ndarray:
    """A minwise token for each coordinate."""
    least = np.full(len(by), np.uint64(2**64 - 1))
    for a in range(0, len(members), 1024):
        np.minimum(least, (members[a : a + 1024] * by[:, None]).min(axis=1), out=least)
    return stir(least)


def root_nodes(tokens: np.ndarray) -> np.ndarray:
    """The record's node in each tree, named by the tree and the token of the tree's own coordinate."""
    trees = np.arange(TREES, dtype=np.uint64)
    return stir(tokens[:: SKETCH // TREES][:TREES] + trees * _MIX[0]).view(np.int64)


def children(node: np.ndarray, level: int, drawn: np.ndarray) -> np.ndarray:
    """Names of the children of node that each record goes to, a row each; drawn: the records' sketches, node: a name each (or one)."""
    count = FIRST if level == 0 else NEXT
    stretch = SKETCH // count  # one coordinate of each stretch, so that all differ
    name = np.broadcast_to(node, len(drawn)).astype(np.int64).view(np.uint64)
    out = np.empty((len(drawn), count), dtype=np.int64)
    for j in range(count):
        at = (stir(name + np.uint64((7 * level + j + 1) * int(_MIX[1]) % 2**64)) % np.uint64(stretch)).astype(np.int64) + j * stretch
        value = drawn[np.arange(len(drawn)), at].astype(np.uint64)
        out[:, j] = stir(name * _MIX[2] + (at.astype(np.uint64) << np.uint64(8)) + value + np.uint64(1)).view(np.int64)
    return out


def sketches(docs: DataFrame) -> DataFrame:
    """doc_id, t (hash of the text), n_shingles, k1, k2 (fingerprint of the set), roots and drawn (sketch) of every row."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        by = _multipliers()
        for batch in batches:
            rows = []
            for s in _sets_of(batch["text"]):
                k1, k2 = np.frombuffer(xxhash.xxh3_128_digest(s.tobytes()), dtype=np.int64)
                tokens = minwise_tokens(s, by) if len(s) else None
                rows.append((len(s), int(k1), int(k2), root_nodes(tokens) if len(s) else None, (tokens & np.uint64(255)).astype(np.uint8).tobytes() if len(s) else None))
            made = pd.DataFrame(rows, columns=["n_shingles", "k1", "k2", "roots", "drawn"])
            yield pd.concat([batch[["doc_id", "t"]].astype({"doc_id": "Int64"}).reset_index(drop=True), made], axis=1)

    named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return named.withColumn("t", F.xxhash64("text")).mapInPandas(run, "doc_id long, t long, n_shingles long, k1 long, k2 long, roots array<long>, drawn binary")


def full_sets(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """rec, grp, n and members (bytes of the sorted set) of wanted (rec, grp, t, id, k1, k2). wanted is read twice: hand in a checkpoint."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for a in range(0, len(batch), TEXTS):
                part = batch.iloc[a : a + TEXTS]
                sets = shingle_sets(part["text"].tolist())
                out = pd.DataFrame({"rec": part["rec"].to_numpy(), "grp": part["grp"].to_numpy(), "n": [len(s) for s in sets], "members": [s.tobytes() for s in sets]})
                keys = [np.frombuffer(xxhash.xxh3_128_digest(m), dtype=np.int64) for m in out["members"]]
                yield out[[k[0] == x and k[1] == y for k, x, y in zip(keys, part["k1"], part["k2"], strict=True)]]

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("at", F.xxhash64("text"))
    asked = small_or_shuffled(wanted)
    here = (F.col("at") == F.col("t")) & F.col("doc_id").eqNullSafe(F.col("id"))
    return texts.join(asked, here).select("rec", "grp", "k1", "k2", "text").mapInPandas(run, "rec long, grp long, n long, members binary")


class Forest:
    def __init__(self, n: int):
        self.up = np.arange(n)

    def find(self, i: int) -> int:
        up = self.up
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return int(i)

    def join(self, i: int, j: int) -> None:
        i, j = self.find(i), self.find(j)
        self.up[max(i, j)] = min(i, j)

    def roots(self) -> np.ndarray:
        up = self.up
        while not (up[up] == up).all():
            up = up[up]
        self.up = up
        return up


class Sketches:
    """Compares records by their sketches: near() never rejects a linked pair but with a chance of some 1e-9."""

    def __init__(self, rows: dict[str, np.ndarray]):
        self.n, self.drawn = rows["n"].astype(np.int64), np.frombuffer(b"".join(rows["drawn"]), dtype=np.uint8).reshape(-1, SKETCH)
        self.held: tuple[np.ndarray, np.ndarray, np.ndarray] | None = None

    def __len__(self) -> int:
        return len(self.n)

    def near(self, i: int, others: np.ndarray) -> np.ndarray:
        if self.held is None or self.held[0] is not others:
            self.held = others, self.n[others], self.drawn[others]
        _, n, drawn = self.held
        sized = PERCENT * np.maximum(self.n[i], n) <= 100 * np.minimum(self.n[i], n)
        return sized & ((drawn == self.drawn[i]).sum(axis=1) >= FAR * SKETCH)


class Sets:
    """Compares records by their full sets."""

    def __init__(self, rows: dict[str, np.ndarray]):
        sets = [np.frombuffer(m, dtype=np.uint64) for m in rows["members"]]
        self.n = np.array([len(s) for s in sets], dtype=np.int64)
        kinds, words = np.unique(np.concatenate(sets), return_inverse=True)
        self.words = words.astype(np.int32)
        del words
        self.ends = np.cumsum(self.n)
        self.mark = np.zeros(len(kinds), dtype=np.int32)
        self.held: tuple[np.ndarray, np.ndarray, np.ndarray] | None = None
        # Two linked sets share one of their (n - ceil(0.85 n) + 1) rarest shingles, in one order of all shingles.
        often = np.bincount(self.words, minlength=len(kinds))
        place = np.argsort(np.argsort(often, kind="stable"), kind="stable")
        self.rarest = []
        for i in range(len(sets)):
            mine = self._words(i)
            self.rarest.append(mine[np.argsort(place[mine])[: len(mine) - -(-PERCENT * len(mine) // 100) + 1]])
        entries = np.concatenate(self.rarest)
        owner = np.repeat(np.arange(len(sets)), [len(r) for r in self.rarest])
        order = np.argsort(entries, kind="stable")
        self.posted = owner[order].astype(np.int32)
        self.first = np.searchsorted(entries[order], np.arange(len(kinds) + 1))

    def __len__(self) -> int:
        return len(self.n)

    def _words(self, i: int) -> np.ndarray:
        return self.words[self.ends[i] - self.n[i] : self.ends[i]]

    def _gather(self, others: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = self.n[others]
        begin = np.cumsum(n) - n
        return self.words[np.repeat(self.ends[others] - n - begin, n) + np.arange(n.sum())], begin

    def near(self, i: int, others: np.ndarray) -> np.ndarray:
        if self.held is None or self.held[0] is not others:
            self.held = others, *self._gather(others)
        _, words, begin = self.held
        mine, rarest = self._words(i), self.rarest[i]
        some = None
        if 8 * (self.first[rarest + 1] - self.first[rarest]).sum() < len(words):
            met = np.zeros(len(self.n), dtype=bool)
            met[np.concatenate([self.posted[self.first[w] : self.first[w + 1]] for w in rarest])] = True
            some = np.flatnonzero(met[others])
            if not len(some):
                return np.zeros(len(others), dtype=bool)
            words, begin = self._gather(others[some])
        self.mark[mine] = 1
        both = np.add.reduceat(self.mark[words], begin)
        self.mark[mine] = 0
        n = self.n[others if some is None else others[some]]
        hit = 100 * both >= PERCENT * (self.n[i] + n - both)
        if some is None:
            return hit
        out = np.zeros(len(others), dtype=bool)
        out[some[hit]] = True
        return out


def connect(rows: Sketches | Sets, forest: Forest, members: np.ndarray) -> None:
    """Joins near members; each is compared with those only that are in no group found so far."""
    left = members
    while len(left) > 1:
        queue, left = [int(left[0])], left[1:]
        while queue and len(left):
            i = queue.pop()
            hit = rows.near(i, left)
            if hit.any():
                new, left = left[hit], left[~hit]
                for j in new.tolist():
                    forest.join(i, j)
                queue += new.tolist()


def ask(rows: Sketches | Sets, forest: Forest, asking: np.ndarray, members: np.ndarray) -> None:
    """Compares each of asking with all members outside its group."""
    for i in asking.tolist():
        others = members[forest.roots()[members] != forest.find(i)]
        if len(others):
            for j in others[rows.near(i, others)].tolist():
                forest.join(i, j)


def grow_tree(node: int, level: int, rows: Sketches, forest: Forest, leaf: int) -> None:
    """All of the tree below a node, in this task."""
    work = [(node, level, np.arange(len(rows)))]
    while work:
        node, level, idx = work.pop()
        if len(idx) > leaf and level < DEPTH:
            drawn = rows.drawn[idx]
            flat = drawn.astype(np.int64) + 256 * np.arange(SKETCH)
            central = np.bincount(flat.ravel(), minlength=256 * SKETCH)[flat].mean(axis=1) >= DENSE * len(idx)
            if central.any():
                connect(rows, forest, idx[central])
                ask(rows, forest, idx[~central], idx[central])
                idx, drawn = idx[~central], drawn[~central]
        if len(idx) <= leaf or level >= DEPTH:
            connect(rows, forest, idx)
            continue
        names = children(np.int64(node), level, drawn)
        for column in names.T:
            order = np.argsort(column, kind="stable")
            cuts = np.flatnonzero(np.append(True, column[order][1:] != column[order][:-1]))
            work += [(int(column[part[0]]), level + 1, idx[part]) for part in np.split(order, cuts[1:]) if len(part) > 1]


def _stars(recs: np.ndarray, forest: Forest) -> tuple[np.ndarray, np.ndarray]:
    root = forest.roots()
    leaf = np.flatnonzero(root != np.arange(len(root)))
    a, b = recs[root[leaf]], recs[leaf]
    return np.minimum(a, b), np.maximum(a, b)


def _tree_of(level: int, leaf: int):
    def work(name: int, rows: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        held = Sketches(rows)
        forest = Forest(len(held))
        grow_tree(name, level, held, forest, leaf)
        return _stars(rows["rec"], forest)

    return work


def _all_of(kind):
    def work(name: int, rows: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        held = kind(rows)
        forest = Forest(len(held))
        connect(held, forest, np.arange(len(held)))
        return _stars(rows["rec"], forest)

    return work


def _asked_of(kind):
    def work(name: int, rows: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        held = kind(rows)
        forest = Forest(len(held))
        _, first, label = np.unique(rows["label"], return_index=True, return_inverse=True)
        for j, k in enumerate(first[label].tolist()):
            forest.join(j, k)
        known = forest.roots().copy()
        ask(held, forest, np.flatnonzero(rows["side"] == 1), np.flatnonzero(rows["side"] == 0))
        moved = np.flatnonzero(forest.roots() != known)  # links between known groups; those inside are known
        a, b = rows["rec"][forest.up[moved]], rows["rec"][moved]
        return np.minimum(a, b), np.maximum(a, b)

    return work


def _by_group(work):
    """Calls work(name, rows of one group as arrays) in partitions sorted by grp; groups may span batches."""

    def groups(rows: pd.DataFrame) -> pd.DataFrame:
        keys = rows["grp"].to_numpy()
        arrays = {c: rows[c].to_numpy() for c in rows.columns if c != "grp"}
        cuts = np.flatnonzero(np.append(True, keys[1:] != keys[:-1]))
        stops = np.append(cuts[1:], len(keys))
        several = stops - cuts > 1
        made = [work(int(keys[a]), {c: v[a:b] for c, v in arrays.items()}) for a, b in zip(cuts[several].tolist(), stops[several].tolist(), strict=True)]
        a, b = (np.concatenate([m[c] for m in made]) if made else np.empty(0, dtype=np.int64) for c in (0, 1))
        apart = a != b  # heads stand twice in a chunk
        return pd.DataFrame({"a": a[apart], "b": b[apart]}, dtype="int64")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []
        for batch in batches:
            if not len(batch):
                continue
            keys = batch["grp"].to_numpy()
            other = np.flatnonzero(keys != keys[-1])
            if held and held[-1]["grp"].iloc[-1] == keys[-1] and not len(other):
                held.append(batch)
                continue
            last = int(other[-1]) + 1 if len(other) else 0
            yield groups(pd.concat([*held, batch.iloc[:last]], ignore_index=True) if held else batch.iloc[:last])
            held = [batch.iloc[last:]]
        if held:
            yield groups(pd.concat(held, ignore_index=True))

    return run


def _each_group(rows: DataFrame, work) -> DataFrame:
    """(a, b): star edges of the groups that work finds in each grp of rows."""
    return rows.repartition("grp").sortWithinPartitions("grp").mapInPandas(_by_group(work), "a long, b long")


def _oversized(rows: DataFrame, weight: Column, limit: int) -> DataFrame:
    """grp and held (its weight) of the groups above the limit, checkpointed: at most the total weight over the limit of them."""
    return cut_lineage(rows.groupBy("grp").agg(F.sum(weight).cast("long").alias("held")).filter(F.col("held") > limit))


def _grid(asking: DataFrame, asked: DataFrame, kind, limit: int, weight: Column) -> DataFrame:
    """(a, b): links of asking to asked, both (grp, rec, label, payload), block by block of one group."""
    size = lambda rows, name: rows.groupBy("grp").agg(F.ceil(F.sum(weight) / limit).cast("int").alias(name))
    blocks = cut_lineage(size(asking, "us").join(size(asked, "ms"), "grp"))
    each = lambda count: F.explode(F.sequence(F.lit(0), F.col(count) - 1))
    of = lambda count: F.pmod(F.xxhash64("rec"), F.col(count)).cast("int")
    left = asking.join(blocks, "grp").withColumn("u", of("us")).withColumn("m", each("ms")).withColumn("side", F.lit(1))
    right = asked.join(blocks, "grp").withColumn("m", of("ms")).withColumn("u", each("us")).withColumn("side", F.lit(0))
    both = left.unionByName(right).withColumn("grp", F.xxhash64("grp", "u", "m")).drop("u", "m", "us", "ms")
    return _each_group(both, _asked_of(kind))


def _large_groups(large: DataFrame, kind, limit: int, weight: Column) -> DataFrame:
    """(a, b): links within groups beyond one task, large (grp, rec, held, payload): chunks that share the heads, then the members
    outside the group's largest component against all."""
    parts = F.ceil(F.col("held") / limit).cast("int")
    heads = large.groupBy("grp").agg(F.array_distinct(F.array(*[F.min_by("rec", F.xxhash64("rec", F.lit(s))) for s in range(HEADS)])).alias("heads"))
    shared = large.join(heads, "grp").filter(F.array_contains("heads", F.col("rec"))).drop("heads").withColumn("chunk", F.explode(F.sequence(F.lit(0), parts - 1)))
    dealt = large.withColumn("chunk", F.pmod(F.xxhash64("rec", F.lit(3)), parts))
    chunks = shared.unionByName(dealt.withColumn("chunk", F.col("chunk").cast("int"))).withColumn("grp", F.xxhash64("grp", "chunk")).drop("chunk", "held")
    edges = cut_lineage(_each_group(chunks, _all_of(kind)))
    named = large.drop("held").join(components(edges), F.col("rec") == F.col("id"), "left").withColumn("label", F.coalesce("label", "rec")).drop("id")
    named = cut_lineage(named)
    main = named.groupBy("grp", "label").agg(F.count(F.lit(1)).alias("count")).groupBy("grp").agg(F.max_by("label", F.struct("count", "label")).alias("main"))
    asking = cut_lineage(named.join(main, "grp").filter("label <> main").drop("main"))
    if asking.isEmpty():
        return edges
    return edges.unionByName(_grid(asking, named, kind, limit, weight))


def _split_off(rows: DataFrame, big: DataFrame) -> tuple[DataFrame, DataFrame]:
    """rows in small groups, and rows in big ones with held."""
    named = small_or_shuffled(big)
    return rows.join(named, "grp", "left_anti"), cut_lineage(rows.join(named, "grp"))


def candidate_edges(records: DataFrame) -> DataFrame:
    """(a, b): links that the sketches of records (rec, n, roots, drawn) can't rule out, which connect each candidate group."""
    one = F.lit(1)
    rows = records.select(F.explode("roots").alias("grp"), "rec", "n", "drawn")
    found: list[DataFrame] = []
    for level in range(DEPTH + 1):
        big = _oversized(rows, one, NODE)
        if big.isEmpty():
            found.append(_each_group(rows, _tree_of(level, LEAF)))
            break
        small, large = _split_off(rows, big)
        found.append(_each_group(small, _tree_of(level, LEAF)))
        if level == DEPTH:
            found.append(_large_groups(large, Sketches, NODE, one))
            break
        picks = [F.min_by("drawn", F.xxhash64("rec", F.lit(s))) for s in range(HEADS)]
        flagged = large.join(large.groupBy("grp").agg(F.array(*picks).alias("heads")), "grp").mapInPandas(_flag_central, "grp long, rec long, n long, drawn binary, held long, central boolean")
        flagged = cut_lineage(flagged)
        central, others = flagged.filter("central").drop("central"), flagged.filter("not central").drop("central", "held")
        found.append(cut_lineage(_large_groups(central, Sketches, NODE, one)))
        alone = lambda part: part.withColumn("label", F.col("rec"))
        found.append(_grid(alone(others), alone(central.drop("held")), Sketches, NODE, one))
        rows = cut_lineage(others.mapInPandas(_descend(level), "grp long, rec long, n long, drawn binary"))
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    return out


def _flag_central(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for batch in batches:
        own = np.frombuffer(b"".join(batch["drawn"]), dtype=np.uint8).reshape(-1, 1, SKETCH)
        heads = np.frombuffer(b"".join(b"".join(h) for h in batch["heads"]), dtype=np.uint8).reshape(len(batch), -1, SKETCH)
        yield batch.drop(columns="heads").assign(central=(own == heads).mean(axis=(1, 2)) >= DENSE)[["grp", "rec", "n", "drawn", "held", "central"]]


def _descend(level: int):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            names = children(batch["grp"].to_numpy(), level, np.frombuffer(b"".join(batch["drawn"]), dtype=np.uint8).reshape(-1, SKETCH))
            for column in names.T:
                yield batch.assign(grp=column)

    return run


def _stars_of(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """The components of a partition's edges as stars around their least ids; moved: whether any edge was not of that kind."""
    parts = [b[["a", "b"]].to_numpy() for b in batches if len(b)]
    if not parts:
        return
    pairs = np.unique(np.concatenate(parts), axis=0)
    ids, at = np.unique(pairs, return_inverse=True)
    a, b = at.reshape(-1, 2).T
    label = np.arange(len(ids))
    while (label[a] != label[b]).any():
        low = np.minimum(label[a], label[b])
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        while not (label[label] == label).all():
            label = label[label]
    leaf = np.flatnonzero(label != np.arange(len(ids)))
    yield pd.DataFrame({"a": ids[label[leaf]], "b": ids[leaf], "moved": bool((label[b] != a).any())})


def components(edges: DataFrame) -> DataFrame:
    """(id, label): the least member of the component of each id in edges (a, b), a < b.

    Each round every partition has all edges of its ids and turns them into stars around the least id of each group there; when all
    are such stars already, they are the components. Hubs, ids with many larger neighbours, are not gathered: the edges that leave
    a hub go to its least neighbour, by a broadcast (at most 1 / HOT_SHARE hubs exist), and stand in the partitions of their other ends.
    """
    rows = cut_lineage(edges.select("a", "b"))
    while True:
        limit = max(HUB, int(HOT_SHARE * rows.count()))
        hubs = F.broadcast(cut_lineage(rows.groupBy("a").agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") > limit).select(F.col("a").alias("hub"))))
        lower = cut_lineage(rows.join(hubs, F.col("b") == F.col("hub")).groupBy("hub").agg(F.min("a").alias("least")))
        led = rows.join(F.broadcast(lower), F.col("a") == F.col("hub"), "left").select(F.coalesce("least", "a").alias("a"), "b")
        light = led.join(hubs, F.col("a") == F.col("hub"), "left_anti")
        sides = led.select(F.col("b").alias("x"), "a", "b").unionByName(light.select(F.col("a").alias("x"), "a", "b"))
        rows = cut_lineage(sides.repartition("x").mapInPandas(_stars_of, "a long, b long, moved boolean"))
        if lower.isEmpty() and rows.filter("moved").isEmpty():
            return cut_lineage(rows.groupBy(F.col("b").alias("id")).agg(F.min("a").alias("label")))


def links(docs: DataFrame, records: DataFrame) -> DataFrame:
    """(a, b) with a < b: links between records (rec, id, t, k1, k2, n, roots, drawn) that connect each component."""
    groups = components(candidate_edges(records))
    every = groups.unionByName(groups.select(F.col("label").alias("id"), "label").distinct()).select(F.col("id").alias("rec"), F.col("label").alias("grp"))
    wanted = cut_lineage(records.select("rec", "t", "id", "k1", "k2").join(every, "rec"))
    sets = cut_lineage(full_sets(docs, wanted).dropDuplicates(["rec"]))
    weight = F.col("n")
    big = _oversized(sets, weight, GROUP_SHINGLES)
    if big.isEmpty():
        return _each_group(sets, _all_of(Sets))
    small, large = _split_off(sets, big)
    return _each_group(small, _all_of(Sets)).unionByName(_large_groups(large, Sets, GROUP_SHINGLES, weight))


def _with_components(docs: DataFrame) -> DataFrame:
    """doc_id, t, n_shingles, component_id of every row."""
    base = cut_lineage(sketches(docs))
    sets = base.filter("n_shingles > 0").groupBy("k1", "k2")
    unique = sets.agg(F.min("doc_id").alias("id"), F.coalesce(F.min_by("t", "doc_id"), F.min("t")).alias("t"), F.count(F.lit(1)).alias("copies"), F.first("n_shingles").alias("n"), F.first("roots").alias("roots"), F.first("drawn").alias("drawn"))
    records = cut_lineage(unique.withColumn("rec", F.monotonically_increasing_id()))  # numbers are fixed once they are written
    stars = components(links(docs, records))
    named = records.select("rec", "id", "copies", "k1", "k2").join(stars.withColumnRenamed("id", "rec"), "rec", "left").withColumn("label", F.coalesce("label", "rec"))
    linked = cut_lineage(named.join(stars.select("label").distinct(), "label", "left_semi"))
    names = linked.groupBy("label").agg(F.min("id").alias("component"))
    tied = linked.join(names, "label").select("k1", "k2", "copies", "component")
    alone = named.join(stars.select("label").distinct(), "label", "left_anti").filter("copies > 1").select("k1", "k2", "copies", F.col("id").alias("component"))
    tied = cut_lineage(tied.unionByName(alone))
    out = join_spread(base.select("doc_id", "t", "n_shingles", "k1", "k2").filter("n_shingles > 0"), tied, ["k1", "k2"], "copies", base.count())
    out = out.withColumn("component", F.when(F.col("copies").isNull(), F.col("doc_id")).otherwise(F.col("component")))
    bare = base.filter("n_shingles = 0").withColumn("component", F.col("doc_id"))
    columns = ["doc_id", "t", "n_shingles", F.col("component").alias("component_id")]
    return out.select(*columns).unionByName(bare.select(*columns))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of docs (doc_id, text)."""
    return _with_components(docs).select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False)).alias("kept"))


def keep_one_of_each(docs: DataFrame) -> DataFrame:
    """docs with one row of each component: one with the smallest doc_id, and of rows that share it one with the least text hash.
    Rows of components without any id all stay, as do rows without words; of equal rows of one id and text one stays."""
    rows = cut_lineage(_with_components(docs).select("doc_id", "t", "n_shingles", "component_id").filter("doc_id is not null or component_id is not null"))
    seen = rows.filter("n_shingles > 0").groupBy(F.col("component_id").alias("c")).agg(F.min(F.when(F.col("doc_id") == F.col("component_id"), F.col("t"))).alias("best"), F.count(F.lit(1)).alias("members"))
    several = seen.filter("members > 1")
    met = rows.filter("n_shingles > 0").join(several, F.col("component_id") == F.col("c"))
    chosen = F.coalesce((F.col("doc_id") == F.col("c")) & (F.col("t") == F.col("best")), F.lit(False))
    met = cut_lineage(met.select(F.col("doc_id").alias("near_id"), F.col("t").alias("near_t"), chosen.alias("chosen")))
    here = F.col("near_key").eqNullSafe(F.col("near_id")) & (F.col("near_hash") == F.col("near_t"))
    gone = met.filter("not chosen").select("near_id", "near_t").distinct()
    again = met.filter("chosen").groupBy("near_id", "near_t").count().filter("count > 1").select("near_id", "near_t")
    held = docs.withColumn("near_key", F.col("doc_id").cast("long")).withColumn("near_hash", F.xxhash64(F.col("text").cast("string")))
    gone, again = small_or_shuffled(cut_lineage(gone)), small_or_shuffled(cut_lineage(again))
    kept = held.join(gone, here, "left_anti")
    once = kept.join(again, here, "left_semi").dropDuplicates(["near_key", "near_hash"])
    return kept.join(again, here, "left_anti").unionByName(once).select(*[F.col(f"`{c}`") for c in docs.columns])


def op5_near_dups(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))
