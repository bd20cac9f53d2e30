"""Language-model scores by online logistic context mixing over the bits of whole texts.

A text is its lower-cased words, one space after each, and one end.  Every byte of that
stream is a path of binary decisions along a Huffman tree.  Predictors are bit counts
under the last 1, 2, 3 and 5 bytes - these contexts cross words - and under the word so
far; three of them also know the class of the text, one of CLASSES by its byte pairs, which
is paid for with log2 CLASSES bits.  Two mixers add up the predictors' logits with weights that a gate picks (one gate
looks at how sure the long contexts are, the other at the place in the word and how sure
the word context is); an adaptive map refines each mixer's logit.  Both outputs go into a
last mixer whose weights belong to the document and are moved online, after every
SEGMENT bytes of it.  Above the bytes stands a match predictor: at places picked by their
content (the hash of the last CONTEXT words), one binary decision says whether the words up to the next such place are
those that followed this context most often elsewhere; if so they cost nothing more.
What is coded at a place depends only on what stands before it, so -log2 of the score is
a code length in bits.

Learning uses all documents whose crc32(doc_id) mod 5 is not 1.  Bit counts are counts of
all their bytes; classes are k-means over all of them (CLASS_ROUNDS passes at most; START_DOCS
documents serve for the first centres only); weights of the two mixers are learned over the
distinct contexts, each as often as it occurs: a shard moves them online, after every TURN
decisions, and the shards' moves are merged by their curvature, LEARN_ROUNDS times; then come the maps.  A decision of a
training document does not see its own count; the match predictor leaves out what the
document itself has at the place.

Nothing that grows with the corpus is kept in one place.  Distinct grams (5 bytes, byte)
are dealt into shards by their last 3 bytes of context: a shard has whole contexts of
order 3 and 5 and whole word contexts of 3 bytes and more; shorter ones are bounded by
the alphabet and broadcast.  Documents are dealt into blocks by a hash of doc_id.  The
most common grams and words (COMMON and COMMON_WORDS at most, by their counts) are broadcast; for the
others a block asks by key, and the answers are joined to it.  No key that many blocks
share is in that join.

Special cases: a null or empty text has the end as its only token; a null doc_id counts
as training and not held out; without training documents every count is 0 and
the base score's denominator is 0.5; repeated rows count each; no rows give none; extra
columns are ignored.  Words and contexts of words are told apart by 62-bit fingerprints.
"""

from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..session import cut, keep, plan_bytes, ship, sweep
from . import base, textvec

BLOCK_BYTES, SHARD_GRAMS, LEAST_SHARDS, COMMON, COMMON_WORDS, LEARN_ROUNDS = 2 << 20, 50_000, 48, 1_000_000, 2_000_000, 4
CLASSES, CLASS_ROUNDS, START_DOCS, PROFILE = 6, 10, 2_000, 256
ORDERS = (1, 2, 3, 5)
DEPTH = ORDERS[-1]
SPACE, STOP = 0x20, 0x0A  # neither can be inside a word: ends of a word and of a text
LEVELS, STEP = 33, 10.0  # cells of an adaptive map; logits are kept in tenths
GATES = (16, 24)
SEGMENT, LANES, RIDGE = 64, 256, 400.0
TURN = 16_384  # decisions after which a shard moves the weights of the two gated mixers
CONTEXT, ANCHOR = 3, 64  # words of a match context; one place in ANCHOR is picked
SEEN_LEVELS, TRUST = 8, 2.0
_HIGH = np.uint64(2**64 - 4)


# -- the stream ----------------------------------------------------------


def huffman(weights: np.ndarray) -> list[list[tuple[int, int]]]:
    """For each byte its path of (inner node, bit)."""
    heap = [(float(w), i, i) for i, w in enumerate(weights)]
    heapq.heapify(heap)
    children: dict[int, tuple[int, int]] = {}
    inner = len(weights)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        children[inner] = (a[2], b[2])
        heapq.heappush(heap, (a[0] + b[0], inner, inner))
        inner += 1
    paths: list[list[tuple[int, int]]] = [[] for _ in weights]
    stack: list[tuple[int, list[tuple[int, int]]]] = [(inner - 1, [])]
    while stack:
        node, path = stack.pop()
        if node < len(weights):
            paths[node] = path
        else:
            for bit, child in enumerate(children[node]):
                stack.append((child, [*path, (node - len(weights), bit)]))
    return paths


class Stream:
    """The coded bytes of several texts: grams, the text of each, the place of each word.

    A gram has the byte in its lowest 8 bits, the 5 bytes before it above, the nearest
    lowest, and on top the class of the text."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, centres: np.ndarray | None = None):
        low = textvec.LOWER[data]
        self.group = np.zeros(len(offsets) - 1, np.int64) if centres is None else nearest(profiles(low, offsets), centres)
        self.words = w = textvec.Words(low, offsets)
        n = len(offsets) - 1
        self.count = w.counts()
        size = w.ends - w.starts + 1
        doc = w.doc()
        self.begin = np.concatenate([[0], np.cumsum(size)])[:-1] + doc  # a stop stands before each later text's words
        total = int(size.sum()) + n
        length = np.bincount(doc, size, n).astype(np.int64) + 1
        self.first = np.concatenate([[0], np.cumsum(length)])
        # the bytes of a word follow its start; what is left are spaces and stops
        symbol = np.full(total + 7, SPACE, np.uint8)
        coded = ~textvec.IS_SPACE[low]
        at = np.ones(total, bool)
        at[self.begin + size - 1] = False
        at[self.first[1:] - 1] = False
        symbol[7:][at] = low[coded]
        symbol[7:][self.first[1:] - 1] = STOP
        # eight bytes that end at each place, the place's own lowest
        gram = np.ndarray((total,), ">u8", symbol, strides=(1,)).astype(np.int64) & ((1 << 8 * DEPTH + 8) - 1)
        for place in range(DEPTH):
            early = (self.first[:-1] + place)[length > place]
            own = (1 << 8 * (place + 1)) - 1
            gram[early] = gram[early] & own | sum(STOP << 8 * back for back in range(place + 1, DEPTH + 1))
        gram |= np.repeat(self.group, length) << (8 * DEPTH + 8)
        self.grams, self.length, self.doc = gram, length, doc


def word_context(grams: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(word so far, its last DEPTH bytes at most; number of its bytes, DEPTH at most)."""
    out, place = np.zeros(len(grams), np.int64), np.zeros(len(grams), np.int64)
    alive = np.ones(len(grams), bool)
    for back in range(1, DEPTH + 1):
        byte = (grams >> (8 * back)) & 255
        alive &= (byte != SPACE) & (byte != STOP)
        out |= np.where(alive, byte << (8 * (back - 1)), 0)
        place += alive
    return out, place


# -- predictors and mixers -------------------------------------------------


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -12, 12)))


KINDS = (*ORDERS, "word")
CLASSED = (2, 3, "word")  # contexts that also hold the class of the text


class Speller:
    """Binary decisions of grams, bit counts of their contexts, two mixers and their maps."""

    def __init__(self, weights: np.ndarray):
        paths = huffman(weights)
        self.length = np.array([len(p) for p in paths])
        self.start = np.concatenate([[0], np.cumsum(self.length)])[:-1]
        self.node = np.array([n for p in paths for n, _ in p], np.int64)
        self.bit = np.array([b for p in paths for _, b in p], np.int8)
        self.tallies: dict = {}
        self.mixing = [np.full((g, len(KINDS) + 1), 1.0 / len(KINDS)) for g in GATES]
        self.refined = [np.tile(np.linspace(-8, 8, LEVELS), (g, 1)) for g in GATES]

    def decisions(self, symbols: np.ndarray):
        """(gram of each decision, node, bit)."""
        count = self.length[symbols]
        total = np.cumsum(count)
        where = np.repeat(self.start[symbols] - (total - count), count) + np.arange(total[-1] if len(total) else 0)
        return np.repeat(np.arange(len(symbols)), count), self.node[where], self.bit[where]

    @staticmethod
    def contexts(grams: np.ndarray, kind) -> np.ndarray:
        if kind == "word":
            own, place = word_context(grams)
            out = own | place << (8 * DEPTH)
        else:
            out = (grams >> 8) & ((1 << 8 * kind) - 1)
        return out | (grams >> (8 * DEPTH + 8)) << 50 if kind in CLASSED else out

    def tally(self, kind, contexts: np.ndarray, symbols: np.ndarray, n: np.ndarray) -> tuple:
        """Bit counts of contexts that n times each have these symbols next."""
        owner, node, bit = self.decisions(symbols)
        keys, which = np.unique(contexts[owner] << 8 | node, return_inverse=True)
        w = n[owner].astype(np.float64)
        one = np.bincount(which, w * bit, len(keys))
        return keys, np.bincount(which, w, len(keys)) - one, one

    def with_shard(self, grams: np.ndarray, n: np.ndarray) -> dict:
        """Tallies for the grams of one shard: its own long contexts, the broadcast short ones."""
        own = dict(self.tallies)
        use = n > 0
        grams, n = grams[use], n[use]
        for kind in (3, 5):
            own[kind] = self.tally(kind, self.contexts(grams, kind), grams & 255, n)
        inside = word_context(grams)[1] >= 3
        long = self.tally("word", self.contexts(grams[inside], "word"), grams[inside] & 255, n[inside])
        both = [np.concatenate(x) for x in zip(self.tallies["word"], long)]
        order = np.argsort(both[0], kind="stable")
        own["word"] = tuple(x[order] for x in both)
        return own

    def inputs(self, tallies: dict, grams: np.ndarray, apart: np.ndarray):
        """(gram of each decision, bit, inputs, the two gates); apart: leave the decision's own count out."""
        owner, node, bit = self.decisions(grams & 255)
        x = np.full((len(owner), len(KINDS) + 1), 0.3)
        out = apart[owner].astype(np.float64)
        sure = {}
        for k, kind in enumerate(KINDS):
            keys, zeros, ones = tallies[kind]
            key = self.contexts(grams, kind)[owner] << 8 | node
            at = np.minimum(np.searchsorted(keys, key), max(len(keys) - 1, 0))
            known = keys[at] == key if len(keys) else np.zeros(len(key), bool)
            zero, one = (np.where(known, c[at], 0.0) if len(keys) else np.zeros(len(key)) for c in (zeros, ones))
            zero, one = np.maximum(zero - out * (bit == 0), 0), np.maximum(one - out * bit, 0)
            x[:, k] = np.log((one + 0.4) / (zero + 0.4))
            m = zero + one
            sure[kind] = (m > 0).astype(np.int64) + (m > 3) + (m > 30)
        place = word_context(grams)[1][owner]
        return owner, bit, x, (sure[3] * 4 + sure[5], place * 4 + sure["word"])

    def slopes(self, bit: np.ndarray, x: np.ndarray, gates, w: np.ndarray) -> np.ndarray:
        """What a shard says of both mixers' weights, by gate: curvature, and curvature times move.

        The weights are moved online, after every TURN decisions (with weights w), by a
        Newton step with all curvature met so far."""
        k = x.shape[1]
        turns = -(-len(bit) // TURN)
        parts = []
        for weights, gate in zip(self.mixing, gates):
            moved, sharp = weights.copy(), np.tile(np.eye(k), (len(weights), 1, 1))
            for turn in range(turns):
                each = slice(turn, None, turns)  # dealt, as the decisions lie in the order of their grams
                order = np.argsort(gate[each], kind="stable")
                ends = np.searchsorted(gate[each][order], np.arange(len(weights) + 1))
                order = order * turns + turn
                for g in np.flatnonzero(np.diff(ends)).tolist():
                    own = order[ends[g] : ends[g + 1]]
                    xs, n = x[own], w[own]
                    p = _sigmoid(xs @ moved[g])
                    sharp[g] += (xs * (n * p * (1 - p))[:, None]).T @ xs
                    move = np.linalg.solve(sharp[g], xs.T @ (n * (bit[own] - p)))
                    moved[g] += move / max(1.0, float(np.abs(move).max()))
            sharp -= np.eye(k)
            parts.append(np.concatenate([(sharp @ (moved - weights)[:, :, None])[:, :, 0], sharp.reshape(-1, k * k)], 1))
        return np.concatenate(parts)

    def step(self, slopes: np.ndarray) -> None:
        """Move the weights by what all shards say together, each by its curvature."""
        k, row = len(KINDS) + 1, 0
        for weights in self.mixing:
            for g in range(len(weights)):
                move = np.linalg.solve(slopes[row, k:].reshape(k, k) + np.eye(k), slopes[row, :k])
                weights[g] += move / max(1.0, float(np.abs(move).max()))
                row += 1

    def cells(self, bit: np.ndarray, x: np.ndarray, gates, w: np.ndarray) -> np.ndarray:
        """(ones, all) of each cell of both adaptive maps."""
        parts = []
        for weights, gate in zip(self.mixing, gates):
            cell, size = gate * LEVELS + self._level((weights[gate] * x).sum(1)), len(weights) * LEVELS
            parts.append(np.stack([np.bincount(cell, w * bit, size), np.bincount(cell, w, size)], 1))
        return np.concatenate(parts)

    def refine(self, cells: np.ndarray) -> None:
        row = 0
        for i, g in enumerate(GATES):
            own = cells[row : row + g * LEVELS]
            p = (own[:, 0] + 20 * _sigmoid(np.tile(np.linspace(-8, 8, LEVELS), g))) / (own[:, 1] + 20)
            self.refined[i] = np.log(p / (1 - p)).reshape(g, LEVELS)
            row += g * LEVELS

    @staticmethod
    def _level(z):
        return np.rint((np.clip(z, -8, 8) + 8) * (LEVELS - 1) / 16).astype(np.int64)

    def logits(self, tallies: dict, grams: np.ndarray, apart: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(gram of each decision, both mixers' refined logits in favour of the decision's bit, in tenths)."""
        owner, bit, x, gates = self.inputs(tallies, grams, apart)
        out = np.empty((len(owner), 2), np.int8)
        for i, gate in enumerate(gates):
            z = np.clip((self.mixing[i][gate] * x).sum(1), -8, 8)
            z = (z + self.refined[i][gate, self._level(z)]) * 0.5
            out[:, i] = np.rint(np.clip(np.where(bit == 1, z, -z), -12, 12) * STEP)
        return owner, out


# -- classes of texts ------------------------------------------------------


def profiles(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Roots of the shares of hashed byte pairs of each text, in 255ths."""
    h = np.zeros((len(offsets) - 1, PROFILE))
    for row, (lo, hi) in enumerate(zip(offsets[:-1].tolist(), offsets[1:].tolist())):
        for a in range(lo, hi - 1, 1 << 20):
            own = data[a : min(a + (1 << 20) + 1, hi)]
            pair = (own[:-1].astype(np.uint32) * np.uint32(2654435761) ^ own[1:].astype(np.uint32) * np.uint32(40503)) >> np.uint32(3)
            h[row] += np.bincount(pair.astype(np.uint8), minlength=PROFILE)
    return np.rint(255 * np.sqrt(h / np.maximum(h.sum(axis=1, keepdims=True), 1)))


def first_centres(points: np.ndarray, k: int = CLASSES, rounds: int = 20, starts: int = 10) -> np.ndarray:
    """k-means, the best of several seeded starts; deterministic."""
    if not len(points):
        return np.zeros((1, PROFILE))
    best, least = points[:1], math.inf
    for seed in range(starts):
        rng = np.random.default_rng(seed)
        centres = points[rng.integers(len(points))][None]
        while len(centres) < min(k, len(points)):
            far = _gaps(points, centres).min(1)
            if far.sum() <= 0:
                break
            centres = np.vstack([centres, points[rng.choice(len(points), p=far / far.sum())]])
        for _ in range(rounds):
            own = _gaps(points, centres).argmin(1)
            centres = np.array([points[own == j].mean(0) if (own == j).any() else centres[j] for j in range(len(centres))])
        cost = float(_gaps(points, centres).min(1).sum())
        if cost < least:
            best, least = centres, cost
    return best


def _gaps(points: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return np.maximum((points**2).sum(1)[:, None] - 2 * points @ centres.T + (centres**2).sum(1)[None, :], 0)


def nearest(points: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return (points @ centres.T * -2 + (centres**2).sum(1)).argmin(1)


def classes(df: DataFrame) -> np.ndarray:
    """Class centres from all training documents of df = prepare(docs)."""
    sc = df.sparkSession.sparkContext

    def outline(data, offsets, rows):
        return base.batch({"point": pa.binary()}, point=[p.tobytes() for p in profiles(textvec.LOWER[data], offsets).astype(np.uint8)])

    seen = cut(base.over_texts(df.where("train"), outline, "point binary"))
    first = seen.select("point").orderBy(F.xxhash64("point")).limit(START_DOCS).collect()
    centres = first_centres(np.array([np.frombuffer(r["point"], np.uint8) for r in first], np.float64).reshape(-1, PROFILE))

    def assign(packed):
        def run(batches):
            middle = packed.value
            sums = np.zeros((len(middle), PROFILE + 1))
            for batch in batches:
                points = np.frombuffer(b"".join(batch.column(0).to_pylist()), np.uint8).reshape(-1, PROFILE).astype(np.float64)
                own = nearest(points, middle)
                for j in range(len(middle)):
                    sums[j, :PROFILE] += points[own == j].sum(0)
                sums[:, PROFILE] += np.bincount(own, minlength=len(middle))
            yield _cells(sums)

        return run

    for _ in range(CLASS_ROUNDS):
        sums = _merged(seen.mapInArrow(assign(sc.broadcast(centres)), _CELLS), (len(centres), PROFILE + 1))
        size = sums[:, PROFILE:]
        better = np.where(size > 0, sums[:, :PROFILE] / np.maximum(size, 1), centres)
        if np.array_equal(better, centres):
            break
        centres = better
    return centres


# -- places and matches ------------------------------------------------------


class Places:
    """Picked places of a stream's texts: context, content up to the next place, words covered."""

    def __init__(self, stream: Stream, hashes: np.ndarray):
        w = stream.words
        value, at = w.grams(hashes, CONTEXT)
        doc = stream.doc[at] if len(at) else at
        picked = (value >> np.uint64(40)) % np.uint64(ANCHOR) == 0
        picked &= at + CONTEXT < w.first[doc + 1] if len(at) else picked
        self.first, self.doc, self.context = at[picked] + CONTEXT, doc[picked], value[picked] & _HIGH
        n = len(self.first)
        ends = w.first[self.doc + 1]
        if n:
            follow = np.append(self.first[1:], 0)
            same = np.append(self.doc[1:] == self.doc[:-1], False)
            ends = np.where(same, follow, ends)
        self.last = ends
        self.content = np.zeros(n, np.uint64)
        if n:
            size = self.last - self.first
            total = np.cumsum(size)
            which = np.repeat(self.first - (total - size), size) + np.arange(total[-1])
            up, _ = textvec._table(int(size.max()) + 1)
            place = np.arange(total[-1]) - np.repeat(total - size, size)
            self.content = textvec.mix(np.add.reduceat(textvec.mix(hashes[which]) * up[place], total - size) + size.astype(np.uint64))


def seen_cell(best, total):
    """Cell of a prediction that was right best times of total (Columns or arrays alike)."""
    level = np.minimum(np.frexp(best.astype(np.float64))[1], SEEN_LEVELS) - 1
    return level * 2 + (best < total)


def _seen_cell_sql(best, total):
    return F.least(F.floor(F.log2(best.cast("double"))) + 1, F.lit(SEEN_LEVELS)).cast("int") * 2 - 2 + (best < total).cast("int")


# -- the corpus ----------------------------------------------------------


def prepare(docs: DataFrame) -> DataFrame:
    rest = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("train", F.coalesce(rest != 1, F.lit(True)))


WORD, GRAM, PLACE, TOTALS = 0, 1, 2, 3  # what a gathered key stands for: its two lowest bits
_GATHERED = {"key": pa.int64(), "more": pa.int64(), "n": pa.int64(), "m": pa.int64()}


def _ids(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(distinct values, place of each value among them)."""
    coded = pa.array(values).dictionary_encode()
    return coded.dictionary.to_numpy(), coded.indices.to_numpy()


def _distinct(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(distinct values in order, how often each occurs)."""
    values = np.sort(values)
    head = np.ones(len(values), bool)
    head[1:] = values[1:] != values[:-1]
    at = np.flatnonzero(head)
    return values[at], np.diff(at, append=len(values))


def word_keys(hashes: np.ndarray) -> np.ndarray:
    return (hashes & _HIGH).view(np.int64)


MERGE_ROWS = 2_000_000


def gathered(df: DataFrame, centres: np.ndarray) -> tuple[DataFrame, int]:
    """(key, more, n, m of everything countable in df = prepare(docs), distinct training words).

    n counts training documents' tokens only, m all.  more: for places, the content that follows;
    otherwise 0.  A word that one token alone is (m = 1) is not listed: whoever asks for it knows its count."""
    packed = df.sparkSession.sparkContext.broadcast(centres)

    def count(data, offsets, rows):
        train = np.asarray(rows.column(0).to_numpy(zero_copy_only=False), bool)
        s = Stream(data, offsets, packed.value)
        hashes = s.words.hashes()
        words, long = word_keys(hashes), np.repeat(train, s.length)
        p = Places(s, hashes)
        keys, n, m = [p.context.view(np.int64) | PLACE, np.array([TOTALS, TOTALS + 4])], [train[p.doc].astype(np.int64), np.array([s.count[train].sum(), train.sum()])], []
        m = [np.ones(len(k), np.int64) for k in keys]
        more = np.concatenate([p.content.view(np.int64), [0, 0]])
        for learns in (True, False):
            for values, use, kind in ((words, train[s.doc] == learns, WORD), (s.grams << 2, long == learns, GRAM)):
                own, often = _distinct(values[use])
                keys.append(own | kind)
                n.append(often * learns)
                m.append(often)
        key, n, m = np.concatenate(keys), np.concatenate(n), np.concatenate(m)
        more = np.concatenate([more, np.zeros(len(key) - len(more), np.int64)])
        return base.batch(_GATHERED, key=key, more=more, n=n, m=m)

    def merge(batches):
        """Add up the batches of a task, MERGE_ROWS at a time."""
        held, size = [], 0

        def flush():
            table = pa.Table.from_batches(held).group_by(["key", "more"], use_threads=False).aggregate([("n", "sum"), ("m", "sum")])
            return table.rename_columns({"n_sum": "n", "m_sum": "m"}).select(list(_GATHERED)).combine_chunks().to_batches()

        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size > MERGE_ROWS:
                yield from flush()
                held, size = [], 0
                pa.default_memory_pool().release_unused()
        if held:
            yield from flush()

    found = base.over_texts(df, count, "key long, more long, n long, m long", "train", most=BLOCK_BYTES, then=merge)
    # a task's rows are merged: an aggregate before the shuffle would find little to add up
    found = found.repartition("key", "more").groupBy("key", "more").agg(F.sum("n").alias("n"), F.sum("m").alias("m"))
    word = F.col("key").bitwiseAND(3) == WORD
    seen = Observation()
    found = found.observe(seen, F.count_if(word & (F.col("n") > 0)).alias("distinct"))
    found = keep(found.where(~word | (F.col("m") > 1)), "gathered")
    return found, seen.get["distinct"]


def _kind(found: DataFrame, kind: int) -> DataFrame:
    return found.where(F.col("key").bitwiseAND(3) == kind)


def common_from(counted: DataFrame, most: int = COMMON) -> int:
    """Least power of two so that at most `most` rows of counted(n) have that n or more."""
    level = F.floor(F.log2(F.col("n").cast("double"))).cast("int").alias("level")
    rows = {r["level"]: r["m"] for r in counted.where("n > 0").groupBy(level).agg(F.count("*").alias("m")).collect()}
    total = 0
    for level in range(63, -1, -1):
        total += rows.get(level, 0)
        if total > most:
            return 1 << (level + 1)
    return 1


_CELLS = "cell long, value double"


def _cells(values: np.ndarray) -> pa.RecordBatch:
    flat = values.ravel()
    at = np.flatnonzero(flat)
    return pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(flat[at], pa.float64())], ["cell", "value"])


def _merged(parts: DataFrame, shape: tuple[int, int]) -> np.ndarray:
    out = np.zeros(shape)
    for row in parts.groupBy("cell").agg(F.sum("value").alias("value")).collect():
        out.flat[row["cell"]] = row["value"]
    return out


def short_counts(grams: DataFrame) -> dict:
    """kind -> (contexts, symbols, n) of the contexts that the alphabet bounds: orders 1 and 2, words under 3 bytes."""
    g = F.col("gram")
    byte = lambda j: F.shiftright(g, 8 * j).bitwiseAND(255)
    edge = lambda j: byte(j).isin(SPACE, STOP)
    low = lambda bits: F.shiftright(g, 8).bitwiseAND(bits)
    group = F.shiftleft(F.shiftright(g, 8 * DEPTH + 8), 50)
    word = F.when(edge(1), F.lit(0).cast("long")).when(edge(2), low(255) + (1 << 8 * DEPTH)).when(edge(3), low(65535) + (2 << 8 * DEPTH))
    kinds = F.array(F.struct(F.lit(1).alias("kind"), low(255).cast("long").alias("context")), F.struct(F.lit(2).alias("kind"), (low(65535) + group).alias("context")), F.struct(F.lit(0).alias("kind"), (word + group).alias("context")))
    rows = grams.where("n > 0").select(F.explode(kinds).alias("c"), byte(0).cast("long").alias("symbol"), "n").where("c.context is not null")
    table = rows.groupBy("c.kind", "c.context", "symbol").agg(F.sum("n").alias("n")).toArrow()
    cols = {c: table.column(c).to_numpy() for c in ("kind", "context", "symbol", "n")}
    return {kind: tuple(cols[c][cols["kind"] == code] for c in ("context", "symbol", "n")) for kind, code in ((1, 1), (2, 2), ("word", 0))}


def learn(found: DataFrame) -> tuple[Speller, DataFrame]:
    """(speller without long contexts, shards: grams array, n array) from found = gathered(df)."""
    sc = found.sparkSession.sparkContext
    grams = _kind(found, GRAM).select(F.shiftright("key", 2).alias("gram"), "n")
    short = short_counts(grams)
    _, symbols, n = short[1]
    speller = Speller(np.bincount(symbols, n, 256) + 0.05)
    for kind, (contexts, symbols, n) in short.items():
        speller.tallies[kind] = speller.tally(kind, contexts, symbols, n)
    shards = max(LEAST_SHARDS, -(-grams.count() // SHARD_GRAMS))
    shard = F.pmod(F.xxhash64(F.shiftright("gram", 8).bitwiseAND(0xFFFFFF)), F.lit(shards)).alias("shard")
    # few rows, each of them a shard: what follows runs over them where they lie
    dealt = grams.withColumn("shard", shard).repartition(max(1, shards // 4), "shard")
    dealt = keep(dealt.groupBy("shard").agg(F.collect_list("gram").alias("gram"), F.collect_list("n").alias("n")), "shards")

    def pack(own, tallies, g, n):
        g, n = g[n > 0], n[n > 0]
        owner, bit, x, gates = own.inputs(tallies, g, n > 0)
        small = [bit.astype(np.uint8), np.rint(np.clip(x[:, :-1], -12, 12) * STEP).astype(np.int8), gates[0].astype(np.uint8), gates[1].astype(np.uint8), n[owner].astype(np.float32)]
        return pa.RecordBatch.from_arrays([pa.array([v.tobytes()], pa.binary()) for v in small], list("bxghw"))

    held = keep(over_shards(dealt, sc.broadcast(speller), pack, ", ".join(f"{c} binary" for c in "bxghw")), "inputs")

    def merged(way, shape):
        packed = sc.broadcast(speller)

        def run(batches):
            for batch in batches:
                for row in range(batch.num_rows):
                    b, x, g, h, w = (np.frombuffer(batch.column(i)[row].as_buffer(), t) for i, t in enumerate((np.uint8, np.int8, np.uint8, np.uint8, np.float32)))
                    x = np.column_stack([x.reshape(len(b), len(KINDS)) / STEP, np.full(len(b), 0.3)])
                    yield _cells(getattr(packed.value, way)(b, x, (g.astype(np.int64), h.astype(np.int64)), w.astype(np.float64)))

        return _merged(held.mapInArrow(run, _CELLS), shape)

    k = len(KINDS) + 1
    for _ in range(LEARN_ROUNDS):
        speller.step(merged("slopes", (sum(GATES), k + k * k)))
    speller.refine(merged("cells", (sum(GATES) * LEVELS, 2)))
    return speller, dealt


def over_shards(dealt: DataFrame, packed, fn, schema: str) -> DataFrame:
    """fn(speller, tallies, grams, n) of each shard; narrow."""

    def run(batches):
        for batch in batches:
            for row in range(batch.num_rows):
                g, n = (batch.column(c).slice(row, 1).flatten().to_numpy() for c in (1, 2))
                order = np.argsort(g, kind="stable")
                own = packed.value
                yield fn(own, own.with_shard(g[order], n[order]), g[order], n[order])

    return dealt.mapInArrow(run, schema)


_FACTS = "key long, n long, x binary"


def gram_facts(speller: Speller, dealt: DataFrame) -> DataFrame:
    """key, n, x of every gram: two logits a decision, plain and then with its own count left out."""

    def score(own, tallies, g, n):
        owner, plain = own.logits(tallies, g, np.zeros(len(g), bool))
        _, apart = own.logits(tallies, g, n > 0)
        raw = np.concatenate([plain, apart], 1).tobytes()
        ends = np.cumsum(own.length[g & 255]).astype(np.int32) * 4
        x = pa.Array.from_buffers(pa.binary(), len(g), [None, pa.py_buffer(np.concatenate([[0], ends]).astype(np.int32).tobytes()), pa.py_buffer(raw)])
        return pa.RecordBatch.from_arrays([pa.array(g << 2 | GRAM), pa.array(n), x], ["key", "n", "x"])

    return over_shards(dealt, dealt.sparkSession.sparkContext.broadcast(speller), score, _FACTS)


def place_facts(found: DataFrame) -> tuple[DataFrame, np.ndarray]:
    """(key, n, best, n_best, second, n_second of contexts that can predict; chance of each cell)."""
    rows = _kind(found, PLACE)
    totals = rows.groupBy("key").agg(F.sum("n").alias("total"), F.max(F.struct("n", "more")).alias("top"), F.max((F.col("m") > F.col("n")).cast("int")).alias("asked"), F.count("*").alias("rows"))
    # a context that one training place alone has predicts nothing, unless a held-out text asks
    totals = cut(totals.where("total > 1 or (total > 0 and asked = 1)"))
    # contexts with a thousandth of all rows or more, a thousand of them at most, are not dealt by their key
    bound = max(1_000, (totals.agg(F.sum("rows").alias("n")).first()["n"] or 0) // 1_000)
    best = totals.select("key", F.col("top.more").alias("best"), (F.col("rows") >= bound).alias("hot"))
    hot = F.broadcast(best.where("hot").select("key", "best"))
    seen = rows.where("n > 0")
    other = seen.join(hot.select("key"), "key", "left_anti").join(best.where("not hot").select("key", "best"), "key").unionByName(seen.join(hot, "key"))
    second = other.where("more <> best").groupBy("key").agg(F.max(F.struct("n", "more")).alias("next"))
    facts = cut(totals.join(second, "key", "left").select(
        "key", "total", F.col("top.more").alias("best"), F.col("top.n").alias("n_best"), F.coalesce("next.more", F.lit(0)).alias("second"), F.coalesce("next.n", F.lit(0)).alias("n_second"),
    ))
    c = F.col
    left = c("n_best") - 1
    stays = (left > c("n_second")) | ((left == c("n_second")) & (c("best") > c("second")))
    again = F.struct(F.when(stays, left).otherwise(c("n_second")).alias("best"), stays.cast("int").alias("hit"), c("n_best").alias("w"))
    others = F.struct(c("n_best").alias("best"), F.lit(0).alias("hit"), (c("total") - c("n_best")).alias("w"))
    each = facts.where("total > 1").select("total", F.explode(F.array(again, others)).alias("o")).where("o.w > 0 and o.best > 0")
    table = each.groupBy(_seen_cell_sql(c("o.best"), c("total") - 1).alias("cell")).agg(F.sum(c("o.hit") * c("o.w")).alias("hits"), F.sum("o.w").alias("all")).collect()
    chance = np.full(2 * SEEN_LEVELS, 0.5)
    for r in table:
        chance[r["cell"]] = (r["hits"] + 1) / (r["all"] + 2)
    return facts, chance


class Common:
    """What is broadcast: the most common words and grams, and the learned numbers."""

    def __init__(self, speller: Speller, centres: np.ndarray, words: pa.Table, grams: pa.Table, chance: np.ndarray, totals: tuple[int, int, int]):
        self.length, self.centres, self.chance, self.totals = speller.length, centres, chance, totals
        order = np.argsort(words.column("key").to_numpy())
        self.word_key, self.word_n = (words.column(c).to_numpy()[order] for c in ("key", "n"))
        key = grams.column("key").to_numpy()
        order = np.argsort(key)
        self.gram_key = key[order]
        x = grams.column("x").combine_chunks().take(pa.array(order))
        x = x.combine_chunks() if isinstance(x, pa.ChunkedArray) else x
        size = self.length[(self.gram_key >> 2) & 255]
        self.gram_start = np.concatenate([[0], np.cumsum(size)])
        self.gram_x = np.frombuffer(b"".join(x.to_pylist()), np.int32)  # four logits a decision


def _find(keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.minimum(np.searchsorted(keys, wanted), max(len(keys) - 1, 0))
    return at, (keys[at] == wanted if len(keys) else np.zeros(len(wanted), bool))


def _find_by(order: np.ndarray, keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """_find, asked in the order of what is wanted, which a cache serves better."""
    at, known = np.empty(len(wanted), np.int64), np.empty(len(wanted), bool)
    at[order], known[order] = _find(keys, wanted[order])
    return at, known


class Block:
    """The documents of one block and what they need to know."""

    def __init__(self, table: pa.Table, common: Common):
        data, offsets = textvec.buffers(table.column("text").combine_chunks())
        self.common, self.bytes = common, np.diff(offsets)
        self.train = np.asarray(table.column("train").to_numpy(zero_copy_only=False), bool)
        self.stream = s = Stream(data, offsets, common.centres)
        hashes = s.words.hashes()
        self.word_keys = word_keys(hashes)
        self.places = Places(s, hashes)

    def asks(self) -> np.ndarray:
        """Keys that are not common."""
        c = self.common
        words, grams = _distinct(self.word_keys)[0], _distinct(self.stream.grams)[0] << 2 | GRAM
        rare = [own[~_find(keys, own)[1]] for own, keys in ((words, c.word_key), (grams, c.gram_key))]
        return np.concatenate([*rare, np.unique(self.places.context).view(np.int64) | PLACE])

    def take(self, answers: pa.Table) -> None:
        c, s = self.common, self.stream
        self.words, self.word = _ids(self.word_keys)
        self.grams, self.gram = _ids(s.grams)
        self.word_keys = s.grams = None  # from here on places have the numbers of their words and grams
        by_word, by_gram = np.argsort(self.words), np.argsort(self.grams)
        self.word_at, self.word_known = _find_by(by_word, c.word_key, self.words)
        self.gram_at, self.gram_known = _find_by(by_gram, c.gram_key, self.grams << 2 | GRAM)
        key, n = answers.column("key").to_numpy(), answers.column("n").to_numpy()
        # a word that is neither common nor answered is one token of this block
        self.count = np.bincount(self.word, self.train[s.doc], len(self.words)).astype(np.int64)
        self.count[self.word_known] = c.word_n[self.word_at[self.word_known]]
        own = np.flatnonzero(key & 3 == WORD)
        self.count[by_word[np.searchsorted(self.words, key[own], sorter=by_word)]] = n[own]
        # logits of the distinct grams' decisions: plain, and once more for training documents
        size = c.length[self.grams & 255]
        self.size, self.start = size, np.cumsum(size) - size
        total = int(size.sum())
        self.logits = np.zeros(total, np.int32)
        known = np.flatnonzero(self.gram_known)
        source = c.gram_x[self._ranges(c.gram_start[self.gram_at[known]], size[known])]
        if len(known) == len(size):
            self.logits = source
        else:
            self.logits[self._ranges(self.start[known], size[known])] = source
        own = np.flatnonzero(key & 3 == GRAM)
        at = by_gram[np.searchsorted(self.grams, key[own] >> 2, sorter=by_gram)]
        x = answers.column("x").combine_chunks().take(pa.array(own))
        self.logits[self._ranges(self.start[at], size[at])] = np.frombuffer(b"".join(x.to_pylist()), np.int32)
        own = np.flatnonzero(key & 3 == PLACE)
        x = answers.column("x").combine_chunks().take(pa.array(own))
        order = np.argsort(key[own])
        self.seen_key = key[own][order]
        self.seen = np.frombuffer(b"".join(x.to_pylist()), ">i8").astype(np.int64).reshape(-1, 5)[order]

    @staticmethod
    def _ranges(first: np.ndarray, size: np.ndarray) -> np.ndarray:
        total = np.cumsum(size)
        out = np.arange(total[-1] if len(total) else 0)
        out += np.repeat(first - (total - size), size)
        return out

    def matches(self) -> tuple[np.ndarray, np.ndarray]:
        """(bits that the match decisions of each text cost, words that need no spelling)."""
        p, chance = self.places, self.common.chance
        n_docs = len(self.train)
        covered = np.zeros(len(self.stream.words), bool)
        bits = np.zeros(n_docs)
        at, known = _find(self.seen_key, p.context.view(np.int64) | PLACE)
        if not known.any():
            return bits, covered
        row = self.seen[np.where(known, at, 0)] * known[:, None]
        total, best, n_best, second, n_second = (row[:, i].copy() for i in range(5))
        content, train = p.content.view(np.int64), self.train[p.doc]
        # what the document itself has at such places does not count
        tag = textvec.mix(p.context ^ textvec.mix(p.doc.astype(np.uint64)))
        _, pair = np.unique(tag + textvec.mix(p.content), return_inverse=True)
        own = np.bincount(pair)[pair] * train
        _, whole = np.unique(tag, return_inverse=True)
        total -= np.bincount(whole)[whole] * train
        n_best -= np.where(content == best, own, 0)
        n_second -= np.where(content == second, own, 0)
        change = (n_second > n_best) | ((n_second == n_best) & (second > best))
        best, n_best = np.where(change, second, best), np.where(change, n_second, n_best)
        says = np.flatnonzero(known & (n_best > 0))
        if not len(says):
            return bits, covered
        hit = (content[says] == best[says]).astype(np.float64)
        doc = p.doc[says]
        begin = np.searchsorted(doc, doc)
        before = np.cumsum(hit) - hit
        before -= before[begin]
        n_before = np.arange(len(says)) - begin
        start = chance[seen_cell(n_best[says], np.maximum(total[says], n_best[says]))]
        right = np.clip((before + TRUST * start) / (n_before + TRUST), 1e-4, 1 - 1e-4)
        bits += np.bincount(doc, -np.log2(np.where(hit > 0, right, 1 - right)), n_docs)
        good = says[hit > 0]
        covered[self._ranges(p.first[good], p.last[good] - p.first[good])] = True
        return bits, covered

    def spelled(self, covered: np.ndarray) -> np.ndarray:
        """Bits of each text's bytes, covered words left out; the last mixer learns as it goes."""
        s = self.stream
        n_docs = len(self.train)
        out = np.zeros(n_docs)
        pair = self.logits.view(np.int16)  # of each decision two logits plain, then two with its own count left out
        own = np.where(self.train, 1, 0).astype(np.int32)
        start = (self.start * 2).astype(np.int32 if len(pair) < 1 << 31 else np.int64)
        needed = None
        if covered.any():
            w = s.words
            size = w.ends - w.starts + 1
            needed = np.ones(len(self.gram), bool)
            needed[self._ranges(s.begin[covered], size[covered])] = False
        order = np.argsort(-s.length, kind="stable")
        for lo in range(0, n_docs, LANES):
            docs = order[lo : lo + LANES]
            weights = np.full((2, len(docs)), 0.5)
            curve = np.full((2, len(docs)), RIDGE)
            for at in range(0, int(s.length[docs].max()), SEGMENT):
                lanes = np.flatnonzero(s.length[docs] > at)
                size = np.minimum(s.length[docs[lanes]] - at, SEGMENT)
                place = self._ranges(s.first[docs[lanes]] + at, size)
                if needed is not None:
                    use = needed[place]
                    size = np.add.reduceat(use, np.cumsum(size) - size, dtype=np.int64)
                    place = place[use]
                    lanes, size = lanes[size > 0], size[size > 0]
                    if not len(lanes):
                        continue
                gram = self.gram[place]
                n = self.size[gram]
                done = np.cumsum(n)
                edge = np.concatenate([[0], done[np.cumsum(size) - 1]])
                begin, count = edge[:-1], np.diff(edge)
                # what lies lane after lane is summed by ranges
                which = start[gram]
                which += np.repeat(own[docs[lanes]], size)
                which -= (2 * (done - n)).astype(which.dtype)
                which = np.repeat(which, n)
                which += np.arange(0, 2 * len(which), 2, dtype=which.dtype)
                x = pair[which].view(np.int8)
                a, b = x[::2].astype(np.float32), x[1::2].astype(np.float32)
                z = np.repeat((weights[0, lanes] / -STEP).astype(np.float32), count)
                z *= a
                y = np.repeat((weights[1, lanes] / -STEP).astype(np.float32), count)
                y *= b
                z += y
                np.clip(z, -16, 16, out=z)
                e = np.exp(z, out=z)
                one = np.add(e, np.float32(1), out=y)
                wrong = np.divide(e, one, out=e)
                out[docs[lanes]] += np.add.reduceat(np.log(one), begin)
                sharp = np.divide(wrong, one, out=one)
                for k, v in enumerate((a, b)):
                    curve[k, lanes] += np.add.reduceat(sharp * v * v, begin) / STEP**2
                    pull = np.add.reduceat(wrong * v, begin) / STEP
                    weights[k, lanes] = np.clip(weights[k, lanes] + pull / curve[k, lanes], -0.5, 2.0)
        return out / math.log(2)

    def results(self, table: pa.Table) -> pa.Table:
        s = self.stream
        n_docs = len(self.train)
        n_all, distinct, texts = self.common.totals
        denominator = n_all + 0.5 * (distinct + 1)
        plain = np.log10((self.count + 0.5) / denominator)
        base_score = np.bincount(s.doc, plain[self.word], n_docs) + math.log10((texts + 0.5) / denominator)
        known = np.bincount(s.doc, self.count[self.word] > 0, n_docs).astype(np.int64) + (texts > 0)
        bits, covered = self.matches()
        bits = bits + self.spelled(covered) + math.log2(len(self.common.centres))
        return pa.table({
            "doc_id": table.column("doc_id"), "held_out": pa.array(~self.train), "n_tokens": pa.array(s.count + 1, pa.int64()), "n_known": pa.array(known, pa.int64()),
            "train_tokens": pa.array(np.full(n_docs, n_all), pa.int64()), "base_score": pa.array(base_score), "score": pa.array(-bits * math.log10(2)),
            "bits_per_byte": pa.array(bits / np.maximum(self.bytes, 1)),
        })


_RESULT = {
    "doc_id": pa.int64(), "held_out": pa.bool_(), "n_tokens": pa.int64(), "n_known": pa.int64(), "train_tokens": pa.int64(),
    "base_score": pa.float64(), "score": pa.float64(), "bits_per_byte": pa.float64(),
}
_RESULT_SCHEMA = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, bits_per_byte double"


def _long_bytes(*columns) -> object:
    """Columns of longs as one binary, highest byte first."""
    return F.concat(*[F.unhex(F.lpad(F.hex(c), 16, "0")) for c in columns])


def lm_scores(docs: DataFrame, common: int = COMMON, common_words: int = COMMON_WORDS) -> DataFrame:
    """One row per document: see _RESULT_SCHEMA.  common, common_words: most grams and words that are broadcast."""
    spark = docs.sparkSession
    sc = spark.sparkContext
    df = prepare(docs)
    ship(spark)
    centres = classes(df)
    found, distinct = gathered(df, centres)
    sweep(spark)
    sums = {r["key"]: r["n"] for r in _kind(found, TOTALS).collect()}
    texts = sums.get(TOTALS + 4, 0)
    words = _kind(found, WORD)
    speller, dealt = learn(found)
    grams = keep(gram_facts(speller, dealt), "grams")
    places, chance = place_facts(found)
    often, often_gram = common_from(words, common_words), common_from(grams, common)
    first = Common(
        speller, centres, words.where(F.col("n") >= often).select("key", "n").toArrow(), grams.where(F.col("n") >= often_gram).select("key", "x").toArrow(),
        chance, (sums.get(TOTALS, 0) + texts, distinct + (1 if texts else 0), texts),
    )
    packed = sc.broadcast(first)
    sweep(spark)
    rare = words.where(F.col("n") < often).select("key", "n", F.lit(None).cast("binary").alias("x"))
    rare = rare.unionByName(grams.where(F.col("n") < often_gram))
    rare = rare.unionByName(places.select("key", F.col("total").alias("n"), _long_bytes("total", "best", "n_best", "second", "n_second").alias("x")))
    blocks = max(1, -(-plan_bytes(docs) // BLOCK_BYTES))
    dealt_docs = df.withColumn("block", F.pmod(F.xxhash64(F.coalesce("doc_id", F.lit(-1))), F.lit(blocks)))

    def ask(key, table):
        keys = Block(table, packed.value).asks()
        pa.default_memory_pool().release_unused()
        return pa.table({"block": pa.array(np.full(len(keys), key[0].as_py()), pa.int64()), "key": pa.array(keys)})

    asked = dealt_docs.groupBy("block").applyInArrow(ask, "block long, key long")
    answers = asked.join(rare, "key")

    def score(key, left, right):
        if not left.num_rows:
            return pa.table({n: pa.array([], t) for n, t in _RESULT.items()})
        block = Block(left, packed.value)
        block.take(right)
        out = block.results(left)
        pa.default_memory_pool().release_unused()
        return out

    return dealt_docs.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(score, _RESULT_SCHEMA)


def op7_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scores(base.table(spark, sf_dir, "documents", "doc_id", "text"))
