"""Operator 7: suffix-array removal of repeated byte strings.

A byte goes if a LENGTH-byte string that covers it also starts in a document with a smaller doc_id. Texts equal to one of a smaller id are
found by their digest. For the rest, every window of LENGTH bytes has a key: the hash of twice GRAM bytes that end or begin with its first
gram of the least hash, whichever lies inside. Equal windows have equal keys, so windows whose key occurs in one document only
can't repeat and stay where they are; short grams occur in more and more documents as a table grows, strings twice as long hardly do. The others
are dealt out by key: stretches of text with the same key meet in one shard, each distinct stretch once for each group of documents.
Keys that more than FINE groups hold are dealt by the hash of each whole window instead, so that a frequent string in many
contexts spreads over all shards. Messages between groups and shards are as many as pairs that share a stretch, so at most one a stretch.

A shard keeps one of equal stretches and builds the suffix array of its text by Larsson and Sadakane's refinement (groups of equal prefixes
are sorted again by the ranks twice as deep; ends of stretches sort first). Kasai's pass, in step over all stretches, gives the common
prefix of neighbours in the array; where it falls below LENGTH a new class of equal windows begins, and the least doc_id of a
class is what its windows repeat. Shards of more than PART_BYTES are cut into parts, each with its own arrays, whose sorted classes are
merged by binary search. The least doc_ids return to the documents' groups, which mark, merge and cut the bytes.

Defined results: null and empty texts have no bytes; texts shorter than LENGTH lose none; rows that repeat a doc_id don't cut each other;
rows without an id neither cut nor are cut; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut_lineage, join_spread, spread, table
from .rolling import span_hashes

#: Bytes of a repeated string; bytes of a gram.
LENGTH, GRAM = 50, 16
#: Bytes of a group of documents and, about, of a shard; bytes of a part of a shard; window starts hashed at a time.
GROUP_BYTES, PART_BYTES, STEP = 4 << 20, 3 << 19, 1 << 19
#: Places of the least gram in a window from which its key ends with the gram; before them it begins with it.
BEHIND = (LENGTH - GRAM + 1) // 2
#: Window starts of a stretch; groups that may hold a key before its windows are dealt one by one.
RUN, FINE = 256, 1024
#: Groups for each shard of keys, which take 5 bytes a run of windows: the fewer such shards, the fewer messages.
HASH_GROUPS = 8
#: Bits of a place that fit 64 beside two ranks.
PLACE_BITS = 21
_NOTE = "p long, kind int, b long, x binary, y binary, z binary"
_rng = np.random.default_rng(7)
_BYTE = _rng.integers(1, 2**63, size=256, dtype=np.uint64)
_BASE = np.uint64(0x9E3779B97F4A7C15)


def _stir(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def window_runs(buf: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(start, stop, key, document) of the runs of window starts with one key. ends: where each document of buf ends."""
    found = []
    last = len(buf) - LENGTH + 1
    for a in range(0, max(0, last), STEP):
        b = min(a + STEP, last)
        h, base = _BYTE[buf[a : b + LENGTH - 1]], np.array([_BASE])
        step = 1
        while step < GRAM:
            h = h[:-step] * base + h[step:]
            base, step = base * base, step * 2
        # 26 bits of the hash, then how far ahead the gram stands: of equal ones the first is the least
        m, width = (_stir(h) >> np.uint64(38)).astype(np.uint32) << np.uint32(6), 1
        while width * 2 <= LENGTH - GRAM + 1:
            m, width = np.minimum(m[:-width], m[width:] + np.uint32(width)), width * 2
        if rest := LENGTH - GRAM + 1 - width:
            m = np.minimum(m[:-rest], m[rest:] + np.uint32(rest))
        at = (m & np.uint32(63)).astype(np.int32)
        behind = at >= BEHIND
        place = np.arange(len(at), dtype=np.int32) + at
        new = np.ones(len(at), dtype=bool)
        new[1:] = (place[1:] != place[:-1]) | (behind[1:] != behind[:-1])
        edges = ends[(ends > a) & (ends < b)] - a
        new[edges] = True
        start = np.flatnonzero(new)
        place, behind = place[start], behind[start]
        place = np.where(behind, place - GRAM, place)
        key = _stir((h[place] * base + h[place + GRAM]) ^ behind)
        # the least gram of periodic text moves on, its key stays
        new[start[1:]] = key[1:] != key[:-1]
        new[edges] = True
        keep = new[start]
        start, key = start[keep], key[keep]
        stop = np.append(start[1:], len(at))
        doc = np.searchsorted(ends, start + a, side="right")
        stop = np.minimum(stop + a, ends[doc] - LENGTH + 1)
        keep = start + a < stop
        found.append((start[keep] + a, stop[keep], key[keep], doc[keep]))
    if not found:
        none = np.empty(0, dtype=np.int64)
        return none, none, np.empty(0, dtype=np.uint64), none
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def key_names(keys: np.ndarray, shards: int) -> np.ndarray:
    """The shard of each key and, as the last 32 bits, its name there: enough to tell keys of a shard apart but for a few, which are then dealt in vain."""
    return ((keys % np.uint64(shards)) << np.uint64(32)) | (keys >> np.uint64(32))


def _bytes_ahead(text: np.ndarray, left: np.ndarray, count: int) -> np.ndarray:
    """The next count bytes (at most 8) of each place as one number, zeros past the end of its stretch."""
    n, width = len(text), 1
    out = np.concatenate([text, np.zeros(7, dtype=np.uint8)]).astype(np.uint64)
    while width < 8:  # strings of 2, 4 and 8 bytes from two halves
        out = (out[:-width] << np.uint64(8 * width)) | out[width:]
        width *= 2
    held = np.array([((1 << 8 * k) - 1) << 8 * (8 - k) for k in range(count + 1)], dtype=np.uint64)
    return (out[:n] & held[np.minimum(left, count)]) >> np.uint64(8 * (8 - count))


def places_left(lens: np.ndarray) -> np.ndarray:
    """Bytes from each place to the end of its stretch."""
    ends = np.cumsum(lens, dtype=np.int32)
    return np.repeat(ends, lens) - np.arange(ends[-1] if len(ends) else 0, dtype=np.int32)


def _in_order(key: np.ndarray, at: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(places at in the order of their keys, where a new key begins). Equal keys keep the order of places, as Kasai's pass needs it: plain
    numbers sort several times as fast as their indices, so the place is the key's last bits where both fit 64."""
    if bits <= PLACE_BITS:
        key = np.sort((key << np.uint64(bits)) | at.astype(np.uint64))
        at = (key & np.uint64((1 << bits) - 1)).astype(np.int32)
        key >>= np.uint64(bits)
    else:
        by = np.argsort(key, kind="stable")
        key, at = key[by], at[by]
    head = np.ones(len(key), dtype=bool)
    np.not_equal(key[1:], key[:-1], out=head[1:])
    return at, head


def suffix_array(text: np.ndarray, left: np.ndarray) -> np.ndarray:
    """Places of text in the order of their suffixes, which end with their stretch; equal suffixes by place."""
    n, depth = len(text), 5
    slots = np.arange(n, dtype=np.int32)
    bits = max(1, n.bit_length())
    key = (_bytes_ahead(text, left, depth) << np.uint64(3)) | np.minimum(left, depth).astype(np.uint64)
    order, head = _in_order(key, slots, bits)
    del key
    rank = np.empty(n, dtype=np.int32)
    rank[order] = np.maximum.accumulate(np.where(head, slots, 0))
    while len(slots):
        # only groups of several suffixes, some of which go on, are sorted again
        first = np.flatnonzero(head)
        size = np.diff(np.append(first, len(slots)))
        more = (size > 1) & (np.maximum.reduceat(left[order[slots]], first) > depth)
        slots = slots[np.repeat(more, size)]
        if not len(slots):
            break
        at = order[slots]
        ahead = rank[np.minimum(at + depth, n - 1)] + 1
        ahead[left[at] <= depth] = 0
        at, head = _in_order((rank[at].astype(np.uint64) << np.uint64(bits)) | ahead.astype(np.uint64), at, bits)
        order[slots] = at
        rank[at] = np.maximum.accumulate(np.where(head, slots, 0))
        depth *= 2
    return order


def kasai(text: np.ndarray, lens: np.ndarray, order: np.ndarray) -> np.ndarray:
    """Common prefix of each suffix in order (a suffix array of stretches of these lengths) with the one before it.

    The place after i shares with its forerunner at least one byte less than i does. Stretches take this step side by side.
    """
    n, left = len(text), places_left(lens)
    before = np.empty(n, dtype=np.int32)  # the forerunner of each place; the first has none and shares nothing
    before[order[1:]] = order[:-1]
    before[order[:1]] = order[:1]
    limit = np.minimum(left, left[before])
    limit[order[:1]] = 0
    ahead = _bytes_ahead(text, left, 8)
    longest = np.argsort(-lens, kind="stable")
    begin, length = (np.cumsum(lens) - lens)[longest], lens[longest]
    lives = np.searchsorted(-length, -np.arange(int(length[0]) if len(length) else 0), side="left").tolist()
    out, shared = np.zeros(n, dtype=np.int32), np.zeros(len(lens), dtype=np.int32)
    for step, live in enumerate(lives):
        i = begin[:live] + step
        j, most = before[i], limit[i]
        k = np.minimum(np.maximum(shared[:live] - 1, 0), most)
        open_ = np.flatnonzero(k < most)
        while len(open_):
            have = k[open_]
            x = ahead[i[open_] + have] ^ ahead[j[open_] + have]
            # the bits up to the highest one set, from a float's exponent: without the bit below it nothing is rounded up to it
            bits = np.frexp((x & ~(x >> np.uint64(1))).astype(np.float64))[1]
            same = 8 - (bits + 7) // 8
            have = np.minimum(have + same, most[open_])
            k[open_] = have
            open_ = open_[(same == 8) & (have < most[open_])]
        out[i] = shared[:live] = k
    return out[order]


def equal_windows(text: np.ndarray, lens: np.ndarray, size: int = LENGTH) -> tuple[np.ndarray, np.ndarray]:
    """(windows, class): starts of the windows of size bytes in their order, and the number of each one's class of equal windows."""
    left = places_left(lens)
    order = suffix_array(text, left)
    classes = np.cumsum(kasai(text, lens, order) < size)
    whole = left[order] >= size
    _, classes = np.unique(classes[whole], return_inverse=True)
    return order[whole], classes


def least_owner(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> list[np.ndarray]:
    """For each part (text, lengths of its stretches, owner of each): the least owner of each window over all parts, by window start
    (places that begin no window have the greatest number)."""
    ordered = []
    none = np.iinfo(np.int64).max
    for text, lens, owner in parts:
        at, of = equal_windows(text, lens)
        first = np.flatnonzero(np.append(True, of[1:] != of[:-1])) if len(of) else np.empty(0, dtype=np.int64)
        least = np.minimum.reduceat(np.repeat(owner, lens)[at], first) if len(of) else np.empty(0, dtype=np.int64)
        ordered.append((text, at, of, first, least))

    def spell(text: np.ndarray, at: np.ndarray) -> np.ndarray:  # a last byte 1 keeps strings that end with byte 0 apart
        rows = np.lib.stride_tricks.sliding_window_view(text, LENGTH)[at] if len(at) else np.empty((0, LENGTH), dtype=np.uint8)
        return np.ascontiguousarray(np.hstack([rows, np.ones((len(rows), 1), dtype=np.uint8)])).view(f"S{LENGTH + 1}").ravel()

    marked = [spell(text, at[first]) for text, at, _, first, _ in ordered] if len(parts) > 1 else [None]
    keys, least = marked[0], ordered[0][4].copy()
    for new, (_, _, _, _, owner) in zip(marked[1:], ordered[1:], strict=True):
        at = np.searchsorted(keys, new)
        same = (at < len(keys)) & (keys[np.minimum(at, max(0, len(keys) - 1))] == new) if len(keys) else np.zeros(len(new), dtype=bool)
        least[at[same]] = np.minimum(least[at[same]], owner[same])
        keys, least = np.insert(keys, at[~same], new[~same]), np.insert(least, at[~same], owner[~same])
    out = []
    for mine, (text, at, of, _, owner) in zip(marked, ordered, strict=True):
        full = np.full(len(text), none)
        full[at] = (owner if mine is None else least[np.searchsorted(keys, mine)])[of]
        out.append(full)
    return out


class Group:
    """The documents of one group, in an order that does not depend on how they came."""

    def __init__(self, docs: pd.DataFrame, copies: dict[bytes, int]):
        docs = docs.sort_values(["doc_id", "digest"], kind="stable")
        self.ids = [None if pd.isna(i) else int(i) for i in docs["doc_id"]]
        self.texts = [t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b"" for t in docs["text"]]
        self.copy = [i is not None and copies.get(bytes(d), i) < i for i, d in zip(self.ids, docs["digest"], strict=True)]
        self.part = [k for k, (i, c) in enumerate(zip(self.ids, self.copy, strict=True)) if i is not None and not c and len(self.texts[k]) >= LENGTH]
        self.buf = np.frombuffer(b"".join(self.texts[k] for k in self.part), dtype=np.uint8)
        self.ends = np.cumsum([len(self.texts[k]) for k in self.part], dtype=np.int64)
        self.owner = np.array([self.ids[k] for k in self.part], dtype=np.int64)

    def runs(self):
        return window_runs(self.buf, self.ends)

    def stretches(self, hot: np.ndarray, fine: np.ndarray, shards: int):
        """Distinct stretches of text of the runs with a hot key, by shard: {shard: ([bytes], [least owner])}, and each run's place."""
        start, stop, h, doc = self.runs()
        name = key_names(h, spread(shards, HASH_GROUPS))
        at = np.searchsorted(hot, name)
        keep = hot[np.minimum(at, len(hot) - 1)] == name if len(hot) else np.zeros(len(h), dtype=bool)
        start, stop, h, doc, single = start[keep], stop[keep], h[keep], doc[keep], fine[at[keep]] if len(hot) else keep[keep]
        pieces = np.where(single, stop - start, -(-(stop - start) // RUN))
        nth = np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        single, h, doc, end = (np.repeat(x, pieces) for x in (single, h, doc, stop))
        start = np.repeat(start, pieces) + nth * np.where(single, 1, RUN)
        stop = np.where(single, start + 1, np.minimum(end, start + RUN))
        if single.any():
            h = h.copy()
            h[single] = span_hashes(self.buf, start[single], start[single] + LENGTH)
        raw, shard, owner = self.buf.tobytes(), (h % np.uint64(shards)).astype(np.int64).tolist(), self.owner[doc].tolist()
        by: dict[int, tuple[dict[bytes, int], list[int]]] = {}
        places = []
        for s, e, b, o in zip(start.tolist(), stop.tolist(), shard, owner, strict=True):
            known, least = by.setdefault(b, ({}, []))
            k = known.setdefault(raw[s : e + LENGTH - 1], len(least))
            if k == len(least):
                least.append(o)
            elif o < least[k]:
                least[k] = o
            places.append((s, o, b, k))
        return {b: (list(known), least) for b, (known, least) in by.items()}, places


def _copies(notes: pd.DataFrame) -> dict[bytes, int]:
    rows = notes[notes["kind"] == 0]
    return {bytes(x): int.from_bytes(bytes(y), "big", signed=True) for x, y in zip(rows["x"], rows["y"], strict=True)}


def _hot(notes: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Names of hot keys in order, and which of them are dealt window by window."""
    rows = notes[notes["kind"] == 1]
    if not len(rows):
        return np.empty(0, dtype=np.uint64), np.empty(0, dtype=bool)
    hot = np.concatenate([np.frombuffer(x, dtype=np.uint32) | (np.uint64(b) << np.uint64(32)) for b, x in zip(rows["b"].tolist(), rows["x"], strict=True)])
    fine = np.concatenate([np.frombuffer(y, dtype=bool) for y in rows["y"]])
    order = np.argsort(hot)
    return hot[order], fine[order]


def _frame(rows: list[tuple]) -> pd.DataFrame:
    return pd.DataFrame(rows, columns=["p", "kind", "b", "x", "y", "z"]).astype({"p": "int64", "kind": "int32", "b": "int64"})


def _hashes(shards: int):
    def run(docs: pd.DataFrame, notes: pd.DataFrame) -> pd.DataFrame:
        """For each shard the keys in this group, and which of them stand in several documents."""
        if not len(docs):
            return _frame([])
        group = Group(docs, _copies(notes))
        _, _, h, doc = group.runs()
        h, owner = key_names(h, shards), group.owner[doc] if len(doc) else np.empty(0, dtype=np.int64)
        order = np.argsort(h, kind="stable")
        h, owner = h[order], owner[order]
        head = np.flatnonzero(np.append(True, h[1:] != h[:-1])) if len(h) else np.empty(0, dtype=np.int64)
        if not len(head):
            return _frame([])
        several = np.minimum.reduceat(owner, head) != np.maximum.reduceat(owner, head)
        shard, h = (h[head] >> np.uint64(32)).astype(np.int64), h[head].astype(np.uint32)  # names lie by shard
        cuts = np.flatnonzero(np.append(True, shard[1:] != shard[:-1]))
        p = int(docs["p"].iloc[0])
        return _frame([(p, 1, int(shard[a]), h[a:b].tobytes(), several[a:b].tobytes(), None) for a, b in zip(cuts, np.append(cuts[1:], len(h)), strict=True)])

    return run


def _find_hot(limit: int):
    def run(rows: pd.DataFrame) -> pd.DataFrame:
        """For each group its hot keys of this shard: those of several groups or documents."""
        each = [np.frombuffer(x, dtype=np.uint32) for x in rows["x"]]
        several = np.concatenate([np.frombuffer(y, dtype=bool) for y in rows["y"]])
        group = np.repeat(np.arange(len(each)), [len(x) for x in each])
        _, of, count = np.unique(np.concatenate(each), return_inverse=True, return_counts=True)
        hot = ((count > 1) | (np.bincount(of, weights=several) > 0))[of]
        h, group, fine = np.concatenate(each)[hot], group[hot], (count > limit)[of][hot]  # still in the order of groups
        cuts = np.searchsorted(group, np.arange(len(each) + 1))
        return _frame([(p, 1, b, h[a:z].tobytes(), fine[a:z].tobytes(), None) for p, b, a, z in zip(rows["p"].tolist(), rows["b"].tolist(), cuts[:-1].tolist(), cuts[1:].tolist(), strict=True) if z > a])

    return run


def _send(shards: int):
    def run(docs: pd.DataFrame, notes: pd.DataFrame) -> pd.DataFrame:
        if not len(docs):
            return _frame([])
        by, _ = Group(docs, _copies(notes)).stretches(*_hot(notes), shards)
        p = int(docs["p"].iloc[0])
        return _frame([(p, 2, b, b"".join(t), np.array([len(s) for s in t], dtype=np.int32).tobytes(), np.array(least, dtype=np.int64).tobytes()) for b, (t, least) in by.items()])

    return run


def _order_shard(part_bytes: int):
    def run(rows: pd.DataFrame) -> pd.DataFrame:
        """Least owners of the windows of each row's stretches, as runs: x runs of each stretch, y their lengths, z the owners."""
        rows = rows.sort_values("p").reset_index(drop=True)
        known: dict[bytes, int] = {}
        which: list[np.ndarray] = []
        for x, y in zip(rows["x"], rows["y"], strict=True):
            ends = np.cumsum(np.frombuffer(y, dtype=np.int32), dtype=np.int64).tolist()
            which.append(np.array([known.setdefault(x[a:b], len(known)) for a, b in zip([0, *ends], ends, strict=False)], dtype=np.int64))
        owner = np.full(len(known), np.iinfo(np.int64).max)
        for k, z in zip(which, rows["z"], strict=True):
            np.minimum.at(owner, k, np.frombuffer(z, dtype=np.int64))
        stretches = list(known)
        lens = np.array([len(s) for s in stretches], dtype=np.int64)
        cuts = np.flatnonzero(np.diff(np.append(-1, (np.cumsum(lens) - lens) // part_bytes)))
        parts = [(np.frombuffer(b"".join(stretches[a:b]), dtype=np.uint8), lens[a:b], owner[a:b]) for a, b in zip(cuts.tolist(), np.append(cuts[1:], len(lens)).tolist(), strict=True)]
        least = np.concatenate(least_owner(parts))
        begin, count = np.cumsum(lens) - lens, lens - LENGTH + 1
        # runs of one least owner inside each stretch
        head = np.append(True, least[1:] != least[:-1])
        head[begin] = True
        head[places_left(lens) < LENGTH] = False
        cut = np.flatnonzero(head)
        first = np.searchsorted(cut, np.append(begin, len(least)))
        until = np.append(cut[1:], 0)
        last = first[1:] - 1
        until[last] = begin + count
        size = (until - cut).astype(np.int32)
        out = []
        for p, b, k in zip(rows["p"].tolist(), rows["b"].tolist(), which, strict=True):
            per = first[k + 1] - first[k]
            at = np.repeat(first[k] - (np.cumsum(per) - per), per) + np.arange(per.sum())
            out.append((p, 2, b, per.astype(np.int32).tobytes(), size[at].tobytes(), least[cut[at]].tobytes()))
        return _frame(out)

    return run


def _cut(shards: int):
    def run(docs: pd.DataFrame, notes: pd.DataFrame) -> pd.DataFrame:
        columns = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"]
        if not len(docs):
            return pd.DataFrame({c: pd.Series(dtype=t) for c, t in zip(columns, ["Int64", "int64", "int64", "int64", "str", "object"], strict=True)})
        group = Group(docs, _copies(notes))
        _, places = group.stretches(*_hot(notes), shards)
        known = {}
        for b, x, y, z in notes.loc[notes["kind"] == 2, ["b", "x", "y", "z"]].itertuples(index=False):
            per = np.frombuffer(x, dtype=np.int32)
            known[b] = (np.append(0, np.cumsum(per)), np.frombuffer(y, dtype=np.int32), np.frombuffer(z, dtype=np.int64))
        change = np.zeros(len(group.buf) + 1, dtype=np.int32)
        for s, owner, b, k in places:
            cut, lens, least = known[b]
            i = s
            for r in range(cut[k], cut[k + 1]):
                if least[r] < owner:
                    change[i] += 1
                    change[i + lens[r] + LENGTH - 1] -= 1
                i += lens[r]
        gone = np.cumsum(change[:-1]) > 0
        rows, begin = {}, 0
        for k, end in zip(group.part, group.ends.tolist(), strict=True):
            rows[k], begin = gone[begin:end], end
        out = []
        for k, (i, text) in enumerate(zip(group.ids, group.texts, strict=True)):
            mask = rows.get(k)
            if mask is None:
                all_gone = group.copy[k] and len(text) >= LENGTH
                removed, spans, kept = (len(text), 1, b"") if all_gone else (0, 0, text)
            else:
                removed, spans = int(mask.sum()), int(mask[0]) + int((mask[1:] & ~mask[:-1]).sum())
                kept = np.frombuffer(text, dtype=np.uint8)[~mask].tobytes() if removed else text
            out.append((i, len(text), removed, spans, hashlib.sha256(kept).hexdigest(), kept))
        made = pd.DataFrame(out, columns=columns)
        made["doc_id"] = made["doc_id"].astype("Int64")
        return made

    return run


def remove_repeats(docs: DataFrame, group_bytes: int = GROUP_BYTES, part_bytes: int = PART_BYTES, fine: int = FINE) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and kept (the bytes that stay) for each row of docs (doc_id, text)."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    total, rows = docs.agg(F.sum(F.octet_length("text")), F.count(F.lit(1))).first()
    groups = shards = spread(total or 0, group_bytes)
    docs = docs.withColumn("digest", F.substring(F.unhex(F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256)), 1, 16))
    docs = docs.withColumn("p", F.pmod(F.xxhash64("doc_id"), F.lit(groups)))
    named = docs.filter("doc_id is not null").select("doc_id", "digest", "p")
    first = named.groupBy("digest").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last"), F.count(F.lit(1)).alias("copies")).filter("first < last").drop("last")
    copies = join_spread(named, cut_lineage(first), ["digest"], "copies", rows).filter("doc_id > first").select("p", "digest", "first").distinct()
    blank = F.lit(None).cast("binary")
    note = lambda kind, b, x, y: [F.col("p"), F.lit(kind).alias("kind"), b.alias("b"), x.alias("x"), y.alias("y"), blank.alias("z")]
    copies = cut_lineage(copies.select(*note(0, F.lit(0).cast("long"), F.col("digest"), F.unhex(F.lpad(F.hex("first"), 16, "0")))))
    held = docs.groupBy("p")
    hashes = held.cogroup(copies.groupBy("p")).applyInPandas(_hashes(spread(groups, HASH_GROUPS)), _NOTE)
    notes = copies.unionByName(hashes.groupBy("b").applyInPandas(_find_hot(fine), _NOTE))
    sent = docs.groupBy("p").cogroup(notes.groupBy("p")).applyInPandas(_send(shards), _NOTE)
    found = notes.unionByName(sent.groupBy("b").applyInPandas(_order_shard(part_bytes), _NOTE))
    return docs.groupBy("p").cogroup(found.groupBy("p")).applyInPandas(_cut(shards), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")


def op7_repeats(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents")).drop("kept")
