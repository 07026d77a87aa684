"""Language-model scores by online logistic mixing of hashed-context bit predictors over whole texts.

A text is its words in order (A-Z lower-cased) and one end. Words seen at least twice in training, up to ``LISTED``
of the most frequent, the end, and an escape for all others are the leaves of a Huffman tree; every token is
a run of bits. The last two words' hashed entry names the word that most often followed; if there is one, the first bit
tells whether it comes again, predicted from how often it did and did not. If it does not, the token is a walk
down the tree, and every step one bit. Three predictors know it: the node alone (from the words' counts), the last word and the
node, and the last very frequent word of the text (which tells the language) and the node, both from counts in hashed tables. They
are mixed in the logistic domain at every step, with weights chosen by how often the context was seen and how deep the walk
is (below ``DEEP`` steps as of one depth). Weights, and a last table that refines the mixed probability by its level, are learnt online in the same pass that gathers the counts:
once a task has settled what it has counted first, it predicts all texts that come next and learns from them. They go on
learning while a text is scored: after its first ``SPAN`` words, after twice as many more, and so on, they move by what
the text has shown so far. Every text starts from the same state, so a score depends on the
text and the training texts alone. The bits of a text and its bytes give bits per byte.

A word after an escape is, if it was seen in training, one of the rare words, by absolute discounting of
their counts (the discount from how many were seen once and twice); else it is spelled: each byte, and the
space after the word, is a walk down a Huffman tree of bytes, predicted from up to five bytes before it and from the last
very frequent word, mixed and learnt the same way. As words
seen once are escapes in training, the model knows when new words come.

Words are named by 64 bits and never become objects: a batch of texts is one run of bytes, cut and hashed as a whole.
Training gathers dense chunks of the tables (their size follows the number of training words up to a
bound) from as many tasks as the cluster runs at once. All training words are counted: listed ones are looked up in
the scan, the rest meet the table of all counts by one join.

Defined results: null and wordless texts are one end token; null ids hash as the empty text does;
repeated rows are scored one by one; without training documents every count is 0; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import copy
import heapq
import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_of, written

#: words in the list at most; words a worker counts before it hands them on; frequent words that tell the language
LISTED, HELD, TOPICS = 262_144, 2_000_000, 64
#: slots of each table: two for each training token, within these powers of two
LEAST, MOST = 12, 21
#: words after which a text's own weights move first (then after spans ever twice as long), and how fast; bytes in a batch of texts
SPAN, FAST, BYTES = 64, 0.02, 300_000
#: levels of the refined probability, and how many bits its learnt value weighs against the text's own
STEPS, FIRM = 33, 200.0
#: depths of a walk that are told apart (every step is predicted from contexts); gates: how often the last word and node were seen and the depth, or the followed word's state
DEEP, SEEN, FOLLOWED = 32, 7, 7
GATES = SEEN * DEEP + FOLLOWED
#: power of two of the slots of frequent words and nodes
TOPIC_POWER = 20
#: contexts of a spelled byte: (bytes before it, with the topic or without), power of two of each one's slots, and gates
SPELLED, SPELL_POWER = ((2, True), (3, True), (4, True), (5, False)), 20
SPELL_GATES = 8 * 6
#: bits between two moves of the learnt weights, their rate and what steadies them
STEP, RATE, STEADY = 32_768, 0.3, 20.0
#: bits a task counts before it settles them, to predict and learn from the texts that come next: a share of those so far, within bounds
SHARE, SOONEST, LATEST = 0.4, 200_000, 3_000_000
#: entries of a chunk of counts on its way to the driver, and the unit of sums that must not depend on their order
CHUNK, POINT = 1 << 13, float(1 << 20)
#: bits of a leaf's number in an entry; the bits above check the context
LEAF = 19

_MIX = np.uint64(0x9E3779B97F4A7C15)
_NODE = np.uint64(0xD1B54A32D192ED03)


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 5 == 1


# --- trees and contexts ---


def huffman(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(parent, side) of a Huffman tree's nodes: leaves 0..n-1, then inner nodes, the root last. Needs two leaves."""
    heap = [(max(int(c), 1), i) for i, c in enumerate(counts)]
    heapq.heapify(heap)
    n = len(heap)
    parent, side = np.zeros(2 * n - 1, np.int32), np.zeros(2 * n - 1, np.int8)
    for k in range(n, 2 * n - 1):
        a = heapq.heappop(heap)
        b = heap[0]
        parent[a[1]] = parent[b[1]] = k
        side[b[1]] = 1
        heapq.heapreplace(heap, (a[0] + b[0], k))
    return parent, side


class Tree:
    """Every leaf's inner nodes and bits from the root (``step``, side by side), and each inner node's log odds from the leaves' counts (``each``).

    All steps are kept, whatever the depth; those below ``keep`` steps count as of one depth. ``rest``, the log10 probability
    of steps that are not kept, is 0 for every leaf.
    """

    def __init__(self, counts: np.ndarray, shape: tuple[np.ndarray, np.ndarray] | None = None, keep: int = 1 << 30):
        n = len(counts)
        parent, side = shape or huffman(counts)
        mass, whole = np.maximum(counts, 0).astype(np.float64), np.zeros(n, np.int32)
        ones, both = np.zeros(n - 1), np.zeros(n - 1)
        for leaf, at in self._climb(n, parent):
            up = parent[at] - n
            both += np.bincount(up, mass[leaf], n - 1)
            ones += np.bincount(up, mass[leaf] * side[at], n - 1)
            whole[leaf] += 1
        odds = np.log((ones + 0.4) / (both - ones + 0.4)).astype(np.float32)
        self.keep, self.length, self.rest = keep, whole.astype(np.int64), np.zeros(n)
        self.offset = np.cumsum(self.length) - self.length
        self.step, self.each = np.zeros(int(self.length.sum()), np.int32), odds
        for k, (leaf, at) in enumerate(self._climb(n, parent)):
            self.step[self.offset[leaf] + whole[leaf] - 1 - k] = (parent[at] - n) * 2 + side[at]

    @property
    def bit(self) -> np.ndarray:
        return (self.step & 1).astype(np.int8)

    @property
    def odds(self) -> np.ndarray:
        return self.each[self.step >> 1]

    @staticmethod
    def _climb(n: int, parent: np.ndarray):
        """(leaves not yet at the root, where they are) step by step upwards."""
        leaf, at, root = np.arange(n), np.arange(n), 2 * n - 2
        while len(leaf):
            yield leaf, at
            at = parent[at]
            go = at != root
            leaf, at = leaf[go], at[go]

    def salt(self, at: np.ndarray) -> np.ndarray:
        """What tells the nodes of the given places apart in a hash."""
        return salt_of(self.step[at])

    def walk(self, leaf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(steps to each leaf, depth and place in ``step`` of every step)."""
        size = self.length[leaf]
        begin = np.cumsum(size) - size
        every = np.arange(int(size.sum()), dtype=np.int32)
        depth = every - np.repeat(begin.astype(np.int32), size)
        return size, np.minimum(depth, self.keep - 1), every + np.repeat((self.offset[leaf] - begin).astype(np.int32), size)


def salt_of(step: np.ndarray) -> np.ndarray:
    """What tells the nodes of the given steps apart in a hash."""
    with np.errstate(over="ignore"):
        return (step >> 1).astype(np.uint64) * _NODE


def context_names(ids: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the word before each token and of the two before it, within its text; ``first`` marks where texts start."""
    with np.errstate(over="ignore"):
        one, two = np.zeros(len(ids), np.uint64), np.zeros(len(ids), np.uint64)
        one[1:] = ids[:-1]
        one[first] = 0
        two[1:] = one[:-1]
        two[first] = 0
        a = (one + np.uint64(1)) * _MIX
        a ^= a >> np.uint64(29)
        b = (a ^ (two * np.uint64(0xBF58476D1CE4E5B9))) * _MIX
        b ^= b >> np.uint64(31)
    return a, b * _MIX


def slots_of(names: np.ndarray, salt: np.ndarray, power: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = names + salt
        h *= _MIX
    h >>= np.uint64(64 - power)
    return h.astype(np.int32)


def followed(names: np.ndarray, power: int) -> tuple[np.ndarray, np.ndarray]:
    """(slot, check) of a context of two words."""
    return (names >> np.uint64(64 - power)).astype(np.int64), ((names >> np.uint64(8)) & np.uint64((1 << 31 - LEAF) - 1)).astype(np.int64)


_LOG = np.log(np.arange(1 << 16) + 0.4).astype(np.float32)
_BITS = np.minimum(np.ceil(np.log2(np.arange(1 << 16) + 1)), 15).astype(np.int8)


class Counts:
    """Zeros and ones of a table's slots while a task gathers them, and what they say, worked out anew where a settling has changed them."""

    def __init__(self, power: int):
        self.n, self.wait = np.zeros(2 << power, np.int32), []
        self.odd, self.seen = np.zeros(1 << power, np.float32), np.zeros(1 << power, np.int8)

    def add(self, slot: np.ndarray, bit: np.ndarray) -> None:
        self.wait.append(slot * 2 + bit)

    def settle(self) -> None:
        if self.wait:
            at = np.sort(np.concatenate(self.wait))
            edge = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1], [True]])) if len(at) else np.zeros(1, np.int64)
            at = at[edge[:-1]]
            self.n[at] += np.diff(edge).astype(np.int32)
            self.wait, slot = [], at >> 1
            slot = slot[np.concatenate([[True], slot[1:] != slot[:-1]])[: len(slot)]]
            n0, n1 = (np.minimum(self.n[2 * slot + k], 65535) for k in (0, 1))
            self.odd[slot], self.seen[slot] = _LOG[n1] - _LOG[n0], _BITS[np.minimum(n0 + n1, 65535)]

    def look(self, slot: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return self.odd[slot], self.seen[slot]

    def odds(self, slot: np.ndarray) -> np.ndarray:
        return self.odd[slot]


class Ready:
    """A finished table: log odds of every slot in steps of 1/2048, and how often it was seen in bits, in one number."""

    def __init__(self, packed: np.ndarray):
        n0, n1 = (packed & np.uint32(0xFFFF)).astype(np.int32), (packed >> np.uint32(16)).astype(np.int32)
        odds = np.round((_LOG[n1] - _LOG[n0]) * 2048).astype(np.int32)
        self.both = (odds << 8) | _BITS[np.minimum(n0 + n1, 65535)]

    def look(self, slot: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        both = self.both[slot]
        return (both >> 8).astype(np.float32) * np.float32(1 / 2048), both & 0xFF

    def odds(self, slot: np.ndarray) -> np.ndarray:
        return (self.both[slot] >> 8).astype(np.float32) * np.float32(1 / 2048)


def logit(x: list[np.ndarray], gate: np.ndarray, w: np.ndarray) -> np.ndarray:
    s = w[:, 0][gate] * x[0]
    for k in range(1, len(x)):
        s += w[:, k][gate] * x[k]
    return np.clip(s, -14, 14, out=s)


def level_of(s: np.ndarray) -> np.ndarray:
    return np.clip(s * ((STEPS - 1) / 16) + ((STEPS - 1) / 2 + 0.5), 0, STEPS - 1).astype(np.int32)


class Learner:
    """Weights by gate, learnt online with the curvature that each block of bits shows, and the refining table."""

    def __init__(self, start: np.ndarray):
        self.w, self.mass = start.astype(np.float64).copy(), np.zeros(len(start), np.int64)
        self.hit, self.all = np.zeros(STEPS, np.int64), np.zeros(STEPS, np.int64)

    def learn(self, x: list[np.ndarray], gate: np.ndarray, bit: np.ndarray, turn: np.ndarray | None = None) -> None:
        """Learn from bits as they come, or by ``turn``, the places of the bits in order."""
        n, k = self.w.shape
        for lo in range(0, len(bit), STEP):
            now = np.arange(lo, min(lo + STEP, len(bit))) if turn is None else turn[lo : lo + STEP]
            order = np.argsort(gate[now].astype(np.min_scalar_type(n)), kind="stable")  # bits of one gate side by side
            now = now[order]
            z, g, y = [c[now] for c in x], gate[now], bit[now]
            edge = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1]]))
            met, size = g[edge], np.diff(np.append(edge, len(g)))
            w = self.w[met].astype(np.float32)
            s = np.repeat(w[:, 0], size) * z[0]
            for a in range(1, k):
                s += np.repeat(w[:, a], size) * z[a]
            np.clip(s, -14, 14, out=s)
            p = 1 / (1 + np.exp(-s))
            err, v = y - p, p * (1 - p)
            slope, bend = np.empty((len(met), k)), np.empty((len(met), k, k))
            for a in range(k):
                slope[:, a] = np.add.reduceat(err * z[a], edge)
                weighed = v * z[a]
                for b in range(a, k):
                    bend[:, a, b] = bend[:, b, a] = np.add.reduceat(weighed * z[b], edge)
            self.w[met] += RATE * np.linalg.solve(bend + np.eye(k) * STEADY, slope[:, :, None])[:, :, 0]
            self.mass[met] += size
            level = level_of(s)
            self.all += np.bincount(level, minlength=STEPS)
            self.hit += np.bincount(level, y, STEPS).astype(np.int64)

    def rows(self, first: int) -> pd.DataFrame:
        """(i, w, m): weights by how many bits their gate had, then the refining table, in whole numbers."""
        m = np.repeat(np.minimum(self.mass, 1 << 20), self.w.shape[1])
        w = np.round(np.round(self.w.ravel() * POINT) * m / 256).astype(np.int64)
        i = first + np.arange(len(w) + STEPS)
        return pd.DataFrame({"i": i.astype(np.int32), "w": np.concatenate([w, self.hit]), "m": np.concatenate([m, self.all])})


def averaged(sums: dict[int, tuple[int, int]], first: int, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(weights, refined) from the sums of all partitions' rows; a gate that none had stays as it started."""
    w = start.astype(np.float64).ravel().copy()
    for k in range(len(w)):
        total, m = sums.get(first + k, (0, 0))
        if m:
            w[k] = total / m * 256 / POINT
    level = 1 / (1 + np.exp(-(np.arange(STEPS) * 16 / (STEPS - 1) - 8)))
    refined = np.array([(sums.get(first + len(w) + i, (0, 0))[0] + 4 * p) / (sums.get(first + len(w) + i, (0, 0))[1] + 4) for i, p in enumerate(level)])
    return w.reshape(start.shape).astype(np.float32), refined


def start_weights() -> np.ndarray:
    """Before training: contexts that were never seen count nothing."""
    w = np.zeros((GATES, 3), np.float32)
    w[: SEEN * DEEP] = (0.2, 0.5, 0.4)
    w[:DEEP] = (0.4, 0.0, 0.6)
    w[SEEN * DEEP :] = (1.0, 0.0, 0.0)
    return w


# --- reading texts ---


_SPACE, _LOWER = np.zeros(256, bool), np.arange(256, dtype=np.uint8)
_SPACE[[32, *range(9, 14)]] = True
_LOWER[65:91] += 32
#: an odd factor and its inverse modulo 2^64, for names that do not depend on where a word lies
_TIMES = 0x5851F42D4C957F2D
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of the factor and of its inverse."""
    if len(_POWERS.get("up", ())) < n:
        size = max(n, 2 * BYTES)
        for name, base in (("up", _TIMES), ("down", pow(_TIMES, -1, 1 << 64))):
            out = np.full(size, base, np.uint64)
            out[0] = 1
            with np.errstate(over="ignore"):
                _POWERS[name] = np.cumprod(out)
    return _POWERS["up"][:n], _POWERS["down"][:n]


class Texts:
    """A batch of texts as one run of bytes: where words start and end, their names, and an end after every text's words."""

    def __init__(self, flat: np.ndarray, offset: np.ndarray):
        n = len(offset) - 1
        self.flat = flat = _LOWER[flat]
        self.flat_start = offset[:-1]
        solid = ~_SPACE[flat]
        edge = np.zeros(len(flat) + 1, bool)
        edge[offset] = True
        begin, stop = solid.copy(), solid.copy()
        begin[1:] &= ~solid[:-1] | edge[1:-1]
        stop[:-1] &= ~solid[1:] | edge[1:-1]
        self.start, self.stop = np.flatnonzero(begin), np.flatnonzero(stop) + 1
        up, down = _powers(len(flat))
        with np.errstate(over="ignore"):
            sums = np.concatenate([[np.uint64(0)], np.cumsum((flat.astype(np.uint64) + np.uint64(1)) * up)])
            name = (sums[self.stop] - sums[self.start]) * down[self.start]
            name ^= name >> np.uint64(32)
            self.name = name * _MIX
        per = np.searchsorted(self.start, offset)
        self.words = np.diff(per)  # of each text
        self.first = per[:-1] + np.arange(n)  # where its tokens start, ends counted
        self.size = self.words + 1
        self.text = np.repeat(np.arange(n, dtype=np.int32), self.size)
        self.is_end = np.zeros(len(self.text), bool)
        self.is_end[self.first + self.words] = True
        self.bytes = np.bincount(self.text[~self.is_end], self.stop - self.start, n).astype(np.int64) + self.size if n else np.zeros(0, np.int64)
        self.ids = np.ones(len(self.text), np.uint64)
        self.ids[~self.is_end] = self.name

    @classmethod
    def of(cls, texts: list[bytes]) -> Texts:
        offset = np.cumsum([0] + [len(t) for t in texts])
        return cls(np.frombuffer(b"".join(texts), np.uint8), offset)

    def word(self, tokens: np.ndarray) -> list[bytes]:
        """The bytes of the given tokens, none of them an end."""
        at = tokens - self.text[tokens]
        return [self.flat[i:j].tobytes() for i, j in zip(self.start[at].tolist(), self.stop[at].tolist())]


def text_batches(column: pa.Array):
    """(rows, Texts) of an Arrow column of strings, about BYTES bytes at a time."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    n, at = len(column), column.offset
    bounds = np.frombuffer(column.buffers()[1], kind)[at : at + n + 1].astype(np.int64) if n else np.zeros(1, np.int64)
    data = column.buffers()[2]
    flat = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    lo = 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(bounds, bounds[lo] + BYTES, side="right")) - 1)
        yield slice(lo, hi), Texts(flat[bounds[lo] : bounds[hi]], bounds[lo : hi + 1] - bounds[lo])
        lo = hi


class Places:
    """Names of listed words to leaves, by the top bits of the names; other words are the escape."""

    BITS = 20

    def __init__(self, names: np.ndarray):
        self.end, self.escape = len(names), len(names) + 1
        order = np.argsort(names, kind="stable")
        self.names, self.leaf = np.append(names[order], np.uint64(0)), np.append(order, 0).astype(np.int32)
        self.begin = np.searchsorted(names[order], np.arange((1 << self.BITS) + 1, dtype=np.uint64) << np.uint64(64 - self.BITS)).astype(np.int32)
        self.begin[-1] = len(names)

    def __call__(self, t: Texts) -> np.ndarray:
        """Leaf of every token."""
        found = np.full(len(t.name), self.escape, np.int32)
        box = (t.name >> np.uint64(64 - self.BITS)).astype(np.int32)
        at, stop = self.begin[box], self.begin[box + 1]
        left = np.flatnonzero(at < stop)
        at, stop = at[left], stop[left]
        while len(left):
            hit = self.names[at] == t.name[left]
            found[left[hit]] = self.leaf[at[hit]]
            at = at + 1
            go = ~hit & (at < stop)
            left, at, stop = left[go], at[go], stop[go]
        out = np.full(len(t.ids), self.end, np.int32)
        out[~t.is_end] = found
        return out


def topics(leaf: np.ndarray, first: np.ndarray, escape: int) -> np.ndarray:
    """For every token the last of the ``TOPICS`` most frequent words before it in its text, plus one; else 0."""
    at = np.arange(len(leaf), dtype=np.int32)
    last = np.where(leaf < min(TOPICS, escape - 1), at, -1)
    last = np.concatenate([[-1], np.maximum.accumulate(last)[:-1]]) if len(leaf) else last
    start = np.repeat(first, np.diff(np.append(first, len(leaf))))
    return np.where(last >= start, leaf[last] + 1, 0)


class Spelling:
    """The bits of words spelled with the space after them: node, bit, gate and slots under every context."""

    def __init__(self, tree: Tree, batch: list[bytes], topic: np.ndarray):
        flat = np.frombuffer(b" ".join(batch) + b" ", np.uint8) if batch else np.zeros(0, np.uint8)
        sizes = np.fromiter(map(len, batch), np.int64, len(batch)) + 1
        first = np.cumsum(sizes) - sizes
        self.word = np.repeat(np.arange(len(batch)), sizes)
        pos, about = np.arange(len(flat)) - first[self.word], topic[self.word].astype(np.uint64)
        self.steps, _, at = tree.walk(flat)
        step = tree.step[at]
        self.bit, salt = (step & 1).astype(np.int8), salt_of(step)
        longest, h, before = max(n for n, _ in SPELLED), np.zeros(len(flat), np.uint64), []
        with np.errstate(over="ignore"):
            for k in range(1, longest + 1):
                inside = np.flatnonzero(pos >= k)
                h = h * _MIX
                h[inside] += flat[inside - k] + np.uint64(1)
                h ^= h >> np.uint64(29)
                before.append(h)
            names = [(before[n - 1] ^ ((about + np.uint64(1)) * np.uint64(0x94D049BB133111EB) if with_topic else np.uint64(n))) * _MIX for n, with_topic in SPELLED]
        self.slots = [slots_of(np.repeat(x, self.steps), salt, SPELL_POWER) for x in names]

    def inputs(self, tables: list) -> tuple[list[np.ndarray], np.ndarray]:
        (first, few), (last, many) = (tables[k].look(self.slots[k]) for k in (0, -2))
        between = [t.odds(s) for t, s in zip(tables[1:-2], self.slots[1:-2])]
        gate = np.minimum(few >> 1, 7).astype(np.int32) * 6 + np.minimum(many >> 1, 5)
        return [first, *between, last, tables[-1].odds(self.slots[-1])], gate


class Steps:
    """The bits of a run of tokens: first whether the followed word comes, where there is one, then walks of the tokens it is not.

    Without ``entries`` nothing is asked and all tokens are walked to, as counts are gathered from all; ``asking`` gives the other form of the same run.
    """

    def __init__(self, tree: Tree, leaf: np.ndarray, ids: np.ndarray, first: np.ndarray, topic: np.ndarray, power: int, entries=None):
        self.tree, self.leaf, self.power = tree, leaf, power
        one, self.two = context_names(ids, first)
        self.asked = np.zeros(0, np.int64)
        walks = np.arange(len(leaf)) if entries is None else np.flatnonzero(self._ask(entries))
        self.walks = walks
        self.size, self.depth, at = tree.walk(leaf[walks])
        step = tree.step[at]
        self.bit, self.node, salt = (step & 1).astype(np.int8), step >> 1, salt_of(step)
        with np.errstate(over="ignore"):
            about = (topic[walks].astype(np.uint64) + np.uint64(7)) * np.uint64(0x94D049BB133111EB)
        self.slots = slots_of(np.repeat(one[walks], self.size), salt, power)
        self.topic_slots = slots_of(np.repeat(about, self.size), salt, TOPIC_POWER)

    def _ask(self, entries) -> np.ndarray:
        """Asks for followed words; marks the tokens that are left to walk to."""
        slot, check = followed(self.two, self.power)
        named = entries["value"][slot].astype(np.int64)
        guess = named & ((1 << LEAF) - 1)
        times = entries["n"][slot]
        self.asked = np.flatnonzero((named >> LEAF == check) & (times > 0) & (guess < len(self.tree.length)))
        self.times, self.misses = times[self.asked].astype(np.int64), entries["miss"][slot[self.asked]].astype(np.int64)
        self.comes = (guess[self.asked] == self.leaf[self.asked]).astype(np.int8)
        stay = np.ones(len(self.leaf), bool)
        stay[self.asked[self.comes == 1]] = False
        return stay

    def asking(self, entries) -> Steps:
        """The same run, asked for followed words first: its walks are some of these."""
        out = copy.copy(self)
        stay = out._ask(entries)
        step = np.flatnonzero(np.repeat(stay, self.size))
        out.walks, out.size = self.walks[stay], self.size[stay]
        for name in ("depth", "node", "bit", "slots", "topic_slots"):
            setattr(out, name, getattr(self, name)[step])
        return out

    def inputs(self, table, about) -> tuple[list[np.ndarray], np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(mixer inputs, gate, bit, token, state) of all bits: questions after the followed word, then walks."""
        x, seen = table.look(self.slots)
        y = about.odds(self.topic_slots)
        gate = np.minimum(seen, SEEN - 1).astype(np.int32) * DEEP + self.depth
        zero = np.zeros(len(self.asked), np.float32)
        state = 1 + np.minimum(self.times - 1, 2) * 2 + (self.misses > 0) if len(self.asked) else np.zeros(0, np.int64)
        sure = np.log((self.times + 0.4) / (self.misses + 0.4)).astype(np.float32) if len(self.asked) else zero
        return (
            [np.concatenate([sure, self.tree.each[self.node]]), np.concatenate([zero + 1, x]), np.concatenate([zero, y])],
            np.concatenate([SEEN * DEEP + state, gate]).astype(np.int32),
            np.concatenate([self.comes, self.bit]) if len(self.asked) else self.bit,
            np.concatenate([self.asked, np.repeat(self.walks, self.size)]),
            np.concatenate([state, np.zeros(len(gate), np.int64)]).astype(np.int32),
        )


ENTRY = np.dtype([("value", "<u4"), ("n", "<u2"), ("miss", "<u2")])


class Followers:
    """For every slot the context of two words seen most in one place, the word that followed it, and how often others did."""

    def __init__(self, power: int):
        self.power = power
        self.value, self.n, self.miss = np.zeros(1 << power, np.uint32), np.zeros(1 << power, np.int32), np.zeros(1 << power, np.int32)

    def __getitem__(self, column: str) -> np.ndarray:
        return {"value": self.value, "n": self.n, "miss": self.miss}[column]

    def add(self, names: np.ndarray, leaf: np.ndarray) -> None:
        slot, check = followed(names, self.power)
        pair, n = np.unique(slot << 32 | check << LEAF | leaf, return_counts=True)
        slot, value = pair >> 32, pair & ((1 << 32) - 1)
        held, some = self.value[slot].astype(np.int64), self.n[slot] > 0
        same = (held == value) & some
        self.n[slot[same]] += n[same]
        miss = np.flatnonzero(~same & (held >> LEAF == value >> LEAF) & some)
        np.add.at(self.miss, slot[miss], n[miss].astype(np.int32))
        rest = np.flatnonzero(~same)
        if not len(rest):
            return
        slot, value, n = slot[rest], value[rest], n[rest]
        first = np.concatenate([[True], slot[1:] != slot[:-1]])  # pairs are in order of slot and value
        most = np.flatnonzero(n == np.maximum.reduceat(n, np.flatnonzero(first))[np.cumsum(first) - 1])
        lead = most[np.concatenate([[True], slot[most[1:]] != slot[most[:-1]]])]
        slot, value, n = slot[lead], value[lead], n[lead]
        wins = n > self.n[slot]
        slot = slot[wins]
        self.value[slot], self.n[slot], self.miss[slot] = value[wins], n[wins], 0

    def entries(self) -> np.ndarray:
        out = np.zeros(len(self.value), ENTRY)
        out["value"], out["n"], out["miss"] = self.value, np.minimum(self.n, 65535), np.minimum(self.miss, 65535)
        return out


def merged(parts: list[np.ndarray]) -> np.ndarray:
    """Entries of one chunk from several tasks: equal ones add up, and of different ones the most frequent stays."""
    rows = np.concatenate(parts)
    place = np.tile(np.arange(len(parts[0])), len(parts))
    some = np.flatnonzero(rows["n"])
    key, back = np.unique(place[some].astype(np.int64) << 32 | rows["value"][some], return_inverse=True)
    n, miss = (np.bincount(back, rows[c][some], len(key)).astype(np.int64) for c in ("n", "miss"))
    slot = key >> 32
    order = np.lexsort((key, -n, slot))
    lead = order[np.flatnonzero(np.concatenate([[True], np.diff(slot[order]) > 0]))] if len(order) else order
    out = np.zeros(len(parts[0]), ENTRY)
    out["value"][slot[lead]], out["n"][slot[lead]], out["miss"][slot[lead]] = key[lead] & ((1 << 32) - 1), np.minimum(n[lead], 65535), np.minimum(miss[lead], 65535)
    return out


class Words:
    """The trained model: ``names`` are the listed words in order of ``counts``; the end and the escape come after them."""

    def __init__(self, names, counts, shape, letters, table, about, entries, spelled, weights, refined, spell_weights, spell_refined):
        self.state = (names, counts, shape, letters, table, about, entries, spelled, weights, refined, spell_weights, spell_refined)
        self._ready()

    def __getstate__(self):
        return self.state

    def __setstate__(self, state):
        self.state = state
        self._ready()

    def _ready(self):
        names, self.counts, shape, letters, table, about, self.entries, spelled, self.weights, self.refined, self.spell_weights, self.spell_refined = self.state
        self.tree, self.letters = Tree(self.counts, shape, DEEP), Tree(letters)
        self.table, self.about, self.spelled = Ready(table), Ready(about), [Ready(t) for t in spelled]
        self.at, self.power = Places(names), int(math.log2(len(table)))

    def spell(self, batch: list[bytes], topic: np.ndarray) -> np.ndarray:
        """log10 probability of each word's bytes and the space after it."""
        out = np.zeros(len(batch))
        for lo in range(0, len(batch), BYTES // 10):
            s = Spelling(self.letters, batch[lo : lo + BYTES // 10], topic[lo : lo + BYTES // 10])
            z = logit(*s.inputs(self.spelled), self.spell_weights)
            p = np.clip((1 / (1 + np.exp(-z)) + self.spell_refined[level_of(z)]) / 2, 1e-6, 1 - 1e-6)
            out[lo : lo + BYTES // 10] = np.bincount(np.repeat(s.word, s.steps), np.log10(np.where(s.bit == 1, p, 1 - p)), len(out[lo : lo + BYTES // 10]))
        return out

    def score(self, t: Texts, span: int = SPAN, spell: np.ndarray | None = None, sums: tuple = ()) -> tuple:
        """(log10 probability of each text but for what follows escapes; text, name and spelling of every word that is not listed;
        for each array of ``sums`` its values summed over the leaves of each text).

        Only texts marked in ``spell`` (all, if not given) can hold new words; the others' spellings are zero.
        """
        n, leaf, lengths, place = len(t.size), self.at(t), t.size, t.text
        topic = topics(leaf, t.first, self.at.escape)
        steps = Steps(self.tree, leaf, t.ids, t.first, topic, self.power, self.entries)
        x, gate, bit, token, state = steps.inputs(self.table, self.about)
        order = np.argsort(-lengths, kind="stable")  # longest first, so that texts still going are a prefix
        rank = np.empty(n, np.int64)
        rank[order] = np.arange(n)
        out = np.bincount(rank[place[steps.walks]], self.tree.rest[leaf[steps.walks]], n).astype(np.float64)
        inside = np.arange(len(leaf), dtype=np.int32) - t.first.astype(np.int32)[place]
        block = np.frexp((inside // span + 1).astype(np.float32))[1].astype(np.uint8) - 1  # spans double
        when = block[token]
        last = int(block.max(initial=0))
        edges = np.concatenate([[0], np.cumsum(np.bincount(when, minlength=last + 1))])
        fixed = logit(x, gate, self.weights)
        if last:
            by = np.argsort(when, kind="stable")
            token, bit, state, fixed, x = token[by], bit[by], state[by], fixed[by], [c[by] for c in x]
        text = rank[place][token]
        own = np.zeros((3, n * FOLLOWED), np.float32)
        hit, all_ = np.tile((self.refined * FIRM).astype(np.float32), n), np.full(n * STEPS, FIRM, np.float32)
        for k, (lo, hi) in enumerate(zip(edges[:-1].tolist(), edges[1:].tolist())):
            if lo == hi:
                continue
            part = slice(lo, hi)
            who, y, s, z, mine = text[part], bit[part], fixed[part], [c[part] for c in x], text[part] * FOLLOWED + state[part]
            if k:
                s = np.clip(s + own[0][mine] * z[0] + own[1][mine] * z[1] + own[2][mine] * z[2], -14, 14)
            cell = who * STEPS + level_of(s)
            p = 1 / (1 + np.exp(-s))
            q = (p + (hit / all_)[cell]) / 2
            m = int(who.max()) + 1
            out[:m] += np.bincount(who, np.log(np.clip(np.abs(q - (y == 0)), 1e-6, 1)), m) / math.log(10)
            if k < last:  # what this block showed moves the next, of the texts that go on
                going = int((lengths > span * ((1 << k + 1) - 1)).sum())
                if going < m:
                    on = np.flatnonzero(who < going)
                    who, y, p, cell, mine, z = who[on], y[on], p[on], cell[on], mine[on], [c[on] for c in z]
                m = int(who.max(initial=-1)) + 1
                have, err = np.bincount(mine, minlength=m * FOLLOWED), y - p
                for j in range(3):
                    own[j, : m * FOLLOWED] += (FAST * np.bincount(mine, err * z[j], m * FOLLOWED) / (1 + have / 256)).astype(np.float32)
                hit[: m * STEPS] += np.bincount(cell, y, m * STEPS)
                all_[: m * STEPS] += np.bincount(cell, minlength=m * STEPS)
        new = np.flatnonzero(leaf == self.at.escape)
        spelled = np.zeros(len(new))
        can = np.flatnonzero(spell[place[new]]) if spell is not None else np.arange(len(new))
        if len(can):
            spelled[can] = self.spell(t.word(new[can]), topic[new[can]])
        return out[rank], place[new], t.ids[new], spelled, [np.bincount(place, v[leaf], n) for v in sums]


# --- training ---


def word_counts(docs: DataFrame) -> DataFrame:
    """(kind, name, c): training counts of every distinct word (kind 0) and of the bytes of words (kind 1)."""

    def run(batches):
        held, n, letters = [], 0, np.zeros(256, np.int64)

        def flush():
            name, c = np.unique(np.concatenate(held), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(np.zeros(len(name), np.int32)), pa.array(name.view(np.int64)), pa.array(c)], names=["kind", "name", "c"])

        for b in batches:
            for _, t in text_batches(b.column(0)):
                held.append(t.name)
                n += len(t.name)
                letters += np.bincount(t.flat, minlength=256)
                if n > HELD:
                    yield flush()
                    held, n = [], 0
        if held:
            yield flush()
        yield pa.RecordBatch.from_arrays([pa.array(np.ones(256, np.int32)), pa.array(np.arange(256)), pa.array(letters)], names=["kind", "name", "c"])

    rows = docs.where(~held_out(docs["doc_id"])).select(text_of(docs).alias("text"))
    return written(rows.mapInArrow(run, "kind int, name long, c long").groupBy("kind", "name").agg(F.sum("c").alias("c")), "words")


def _chunks(total: np.ndarray, first: int = 0) -> pa.RecordBatch:
    """The chunks of a task's table that are not all zero."""
    n = -(-len(total) // CHUNK)
    full = np.zeros(n * CHUNK, total.dtype)
    full[: len(total)] = total
    full = full.reshape(n, CHUNK)
    some = np.flatnonzero(full.view("u1").reshape(n, -1).any(1)).tolist()
    return pa.RecordBatch.from_arrays([pa.array([first + i for i in some], pa.int64()), pa.array([full[i].tobytes() for i in some], pa.binary())], names=["chunk", "n"])


def packed(total: np.ndarray) -> np.ndarray:
    """Counts of zeros and ones, side by side, as one number a slot; counts stay at the largest a half holds."""
    both = np.minimum(total, 65535).astype(np.uint32).reshape(-1, 2)
    return np.ascontiguousarray(both[:, 0] | both[:, 1] << np.uint32(16))


def _gathered(rows: DataFrame, power: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[np.ndarray]]:
    """(table, frequent words' table, entries, spelling tables) of all tasks: equal chunks meet, and reach the driver once."""
    size, rest = 1 << power, (2 << TOPIC_POWER) + len(SPELLED) * (2 << SPELL_POWER)
    words_to = -(-2 * size // CHUNK)
    entries_to = words_to + -(-size // CHUNK)

    def add(f: pd.DataFrame) -> pd.DataFrame:
        chunk = int(f["chunk"].iloc[0])
        if words_to <= chunk < entries_to:
            out = merged([np.frombuffer(raw, ENTRY) for raw in f["n"]]).tobytes()
        else:
            total = np.zeros(CHUNK, np.int64)
            for raw in f["n"]:
                total += np.frombuffer(raw, "<u2")
            out = np.minimum(total, 65535).astype("<u2").tobytes()
        return pd.DataFrame({"chunk": [chunk], "n": [out]})

    counts = np.zeros((words_to * CHUNK,), "<u2")
    entries = np.zeros((entries_to - words_to) * CHUNK, ENTRY)
    more = np.zeros(rest, "<u2")
    for chunk, raw in rows.groupBy("chunk").applyInPandas(add, "chunk long, n binary").toLocalIterator():  # as many as the tables have, whatever the input
        kind, base, into = ("<u2", 0, counts) if chunk < words_to else (ENTRY, words_to, entries) if chunk < entries_to else ("<u2", entries_to, more)
        into[(chunk - base) * CHUNK : (chunk - base + 1) * CHUNK] = np.frombuffer(raw, kind)
    about, letters = more[: 2 << TOPIC_POWER], more[2 << TOPIC_POWER :].reshape(len(SPELLED), -1)
    return packed(counts[: 2 * size]), packed(about), entries[:size], [packed(x) for x in letters]


class Pace:
    """When a task settles its counts. From the first time on (``bits``) there are counts to predict by, and every batch teaches the weights."""

    def __init__(self):
        self.bits = self.pending = 0

    def due(self, n: int) -> bool:
        self.pending += n
        if self.pending < min(max(SHARE * self.bits, SOONEST), LATEST):
            return False
        self.bits, self.pending = self.bits + self.pending, 0
        return True


def train(docs: DataFrame, table: DataFrame, tokens: int, texts_seen: int, listed: int = LISTED) -> Words:
    """The model of all training texts (``tokens`` words and ends), from their counts in ``table``."""
    top = table.where("kind = 0 and c >= 2").orderBy(F.desc("c"), "name").limit(listed).select("name", "c").toArrow()
    names, counts = (top.column(c).combine_chunks().to_numpy(zero_copy_only=False).astype(np.int64) for c in ("name", "c"))
    # a training word of the least listed count would not be listed but for its own occurrence
    least = int(counts[-1]) if len(counts) else 0
    escapes = tokens - texts_seen - int(counts.sum()) + int(counts[counts == least].sum())
    names, counts = names.view(np.uint64), np.concatenate([counts, [texts_seen, max(1, escapes)]])
    power = min(MOST, max(LEAST, math.ceil(math.log2(2 * max(tokens, 1)))))
    spark, size = docs.sparkSession, 1 << power

    letters = np.zeros(256, np.int64)
    for s, n in table.where("kind = 1").select("name", "c").collect():
        letters[s] = n
    shape = huffman(counts)
    kit = spark.sparkContext.broadcast((names, counts, letters, shape))  # at most LISTED words
    texts = docs.where(~held_out(docs["doc_id"])).select(text_of(docs).alias("text"))
    texts = texts.coalesce(max(2, spark.sparkContext.defaultParallelism))  # each task hands on whole tables

    start, start_spell = start_weights(), np.full((SPELL_GATES, len(SPELLED)), 1.2 / len(SPELLED), np.float32)

    def gather(batches):
        names, counts, letters, shape = kit.value
        tree, spelling, at = Tree(counts, shape, DEEP), Tree(letters), Places(names)
        follow, total, about, letter = Followers(power), Counts(power), Counts(TOPIC_POWER), [Counts(SPELL_POWER) for _ in SPELLED]
        by_word, by_letter = Learner(start), Learner(start_spell)
        pace = Pace()
        for t in (t for b in batches for _, t in text_batches(b.column(0))):
            leaf = at(t)
            topic = topics(leaf, t.first, at.escape)
            steps = Steps(tree, leaf, t.ids, t.first, topic, power)
            new = np.flatnonzero(leaf == at.escape)
            s = Spelling(spelling, t.word(new), topic[new])
            if pace.bits:
                known = steps.asking(follow)
                x, gate, bit, token, _ = known.inputs(total, about)
                by_word.learn(x, gate, bit, np.argsort(token, kind="stable"))
                by_letter.learn(*s.inputs(letter), s.bit)
            follow.add(steps.two, leaf.astype(np.int64))
            total.add(steps.slots, steps.bit)
            about.add(steps.topic_slots, steps.bit)
            for table, slot in zip(letter, s.slots):
                table.add(slot, s.bit)
            if pace.due(len(steps.bit) + len(s.bit)):
                for table in (total, about, *letter):
                    table.settle()
        for table in (total, about, *letter):
            table.settle()
        short = lambda t: np.minimum(t.n, 65535).astype("<u2")
        yield _chunks(short(total))
        first = -(-2 * size // CHUNK)
        yield _chunks(follow.entries(), first)
        first += -(-size // CHUNK)
        yield _chunks(np.concatenate([short(t) for t in (about, *letter)]), first)
        learnt = pd.concat([by_word.rows(0), by_letter.rows(start.size + STEPS)])
        yield pa.RecordBatch.from_arrays([pa.array([-1], pa.int64()), pa.array([learnt.to_numpy(np.int64).tobytes()], pa.binary())], names=["chunk", "n"])

    rows = written(texts.mapInArrow(gather, "chunk long, n binary"), "gathered")
    sums: dict[int, tuple[int, int]] = {}
    for (raw,) in rows.where("chunk < 0").select("n").collect():  # a row a task
        for i, w, m in np.frombuffer(raw, np.int64).reshape(-1, 3).tolist():
            a, b = sums.get(i, (0, 0))
            sums[i] = a + w, b + m
    found, about, entries, spelled = _gathered(rows.where("chunk >= 0"), power)
    kit.destroy()
    weights, refined = averaged(sums, 0, start)
    return Words(names, counts, shape, letters, found, about, entries, spelled, weights, refined, *averaged(sums, start.size + STEPS, start_spell))


def scores(docs: DataFrame, listed: int = LISTED) -> DataFrame:
    """One row per row of ``docs``: counts, the unigram base score and the model's log10 probability."""
    table = word_counts(docs)
    once, twice = (F.count(F.when(F.col("c") == k, 1)) for k in (1, 2))
    n, v, n1, n2 = (x or 0 for x in table.where("kind = 0").agg(F.sum("c"), F.count("*"), once, twice).first())
    end_c = docs.where(~held_out(docs["doc_id"])).count()
    n, v = n + end_c, v + (end_c > 0)
    model = train(docs, table, n, end_c, listed)
    held = docs.sparkSession.sparkContext.broadcast(model)
    floor = n + 0.5 * (v + 1)
    off = (n1 + 0.5) / (n1 + 2 * n2 + 1)  # taken off the count of every rare word, for the new ones
    rare_tokens, rare_types = n - int(model.counts[:-1].sum()), v - (len(model.counts) - 2) - (end_c > 0)
    new = math.log10(off * rare_types / rare_tokens) if rare_tokens else 0.0
    kinds = {"rid": pa.int64(), "name": pa.int64(), "tf": pa.int64(), "spelled": pa.float64(), "doc_id": pa.int64(), "held_out": pa.bool_(),
             "n_tokens": pa.int64(), "bytes": pa.int64(), "known": pa.int64(), "base": pa.float64(), "score": pa.float64()}

    def texts(batches):
        model = held.value
        base = np.append(np.log10((model.counts[:-1] + 0.5) / floor), 0)
        known = np.append(model.counts[:-1] > 0, False).astype(np.float64)
        part, row = TaskContext.get().partitionId() << 40, 0
        for b in batches:
            out = b.column(1).to_numpy(zero_copy_only=False)
            for at, t in text_batches(b.column(2)):
                score, whose, name, spelled, (bases, knowns) = model.score(t, spell=out[at], sums=(base, known))  # only held-out texts hold new words
                ids = part + row + np.arange(len(t.size))
                row += len(t.size)
                gap = len(name)
                both = lambda head, x, kind: pa.concat_arrays([pa.nulls(gap, kind) if head is None else pa.array(head, kind), pa.nulls(len(ids), kind) if x is None else pa.array(x, kind)])
                with np.errstate(over="ignore"):
                    own = (ids.astype(np.uint64) * _MIX).view(np.int64)  # the row of the text itself counts no word, whatever it meets
                values = {
                    "rid": (ids[whose], ids), "name": (name.view(np.int64), own), "tf": (np.ones(gap, np.int64), np.zeros(len(ids), np.int64)),
                    "spelled": (spelled, None), "held_out": (None, out[at]), "n_tokens": (None, t.size), "bytes": (None, t.bytes),
                    "known": (None, np.round(knowns).astype(np.int64)), "base": (None, bases), "score": (None, score),
                }
                doc = pa.concat_arrays([pa.nulls(gap, pa.int64()), b.column(0).slice(at.start, at.stop - at.start)])
                yield pa.RecordBatch.from_arrays([doc if c == "doc_id" else both(*values[c], k) for c, k in kinds.items()], names=list(kinds))

    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), held_out(docs["doc_id"]).alias("held_out"), text_of(docs).alias("text"))
    schema = "rid long, name long, tf long, spelled double, doc_id long, held_out boolean, n_tokens long, bytes long, known long, base double, score double"
    met = rows.mapInArrow(texts, schema).join(table.where("kind = 0").select("name", "c"), "name", "left")
    tf, zero, seen = F.col("tf"), F.lit(0.0), F.col("c") > 0
    after = F.when(seen, tf * F.log10((F.col("c") - off) / rare_tokens)).otherwise(F.col("spelled") + tf * new) if rare_tokens else F.col("spelled")
    count = F.coalesce("c", F.lit(0))
    out = met.groupBy("rid").agg(
        F.max("doc_id").alias("doc_id"), F.max("held_out").alias("held_out"), F.max("n_tokens").alias("n_tokens"),
        F.sum(F.coalesce("known", F.lit(0)) + F.when(seen, tf).otherwise(0)).cast("long").alias("n_known"),
        F.sum(F.coalesce("base", zero) + F.when(tf > 0, tf * F.log10((count + 0.5) / floor)).otherwise(zero)).alias("base_score"),
        F.max("bytes").alias("bytes"), F.sum(F.coalesce("score", zero) + F.when(tf > 0, after).otherwise(zero)).alias("score"),
    )
    return out.select(
        "doc_id", "held_out", "n_tokens", "n_known", F.lit(int(n)).cast("long").alias("train_tokens"), "base_score", "score",
        (-F.col("score") * math.log2(10) / F.col("bytes")).alias("bits_per_byte"),
    )
