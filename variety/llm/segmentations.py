"""Distinct sampled segmentations of texts into sentence pieces, by Gumbel top-k.

A segmentation's weight is the product of its pieces' weights, over the lattice of all pieces.
The k segmentations of largest Gumbel-perturbed log-probability are a sample without
replacement. They come out of a best-first search from the top down: a subproblem is a prefix and
the edges excluded after it, its priority the largest perturbed value below it, drawn
as a Gumbel of its mass, truncated at its parent's. Taking the best one completes a segmentation
and leaves a subproblem at each of its later steps. All draws come from hashes of the row's key.
"""

from __future__ import annotations

import heapq
import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bytescan as B
from .common import slices, string_buffers, table, text_frame
from .tokens import vocabulary_path

SPACE = "▁"
SAMPLES = 2
#: The file ranks its pieces; a piece's weight falls with its rank to this power.
RANK_POWER = 1.0
MOST_PIECE = 16
SLICE = 1 << 20
#: Edges that a worker keeps from slice to slice, at some 35 bytes each.
MOST_EDGES = 1 << 22
#: Bits of a cumulated probability.
FRACTION = 52


_BASE = B.BASES[0]
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))


def _code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4").astype(np.int64)


def _prefix_sums(points: np.ndarray) -> np.ndarray:
    """Polynomial hashes of all prefixes; a difference, divided by the base's power, is a substring's."""
    return np.append(np.zeros(1, np.uint64), np.cumsum(B.mix64(points.astype(np.uint64) + np.uint64(1)) * B.powers(len(points), _BASE)))


class Pieces:
    """The vocabulary: log-weights by string, ids, and the ids of single bytes."""

    def __init__(self, path: str, power: float = RANK_POWER):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        n = model.get_piece_size()
        self.weight, self.bytes = {}, [0] * 256
        self.strings = [model.id_to_piece(i) for i in range(n)]
        for i, s in enumerate(self.strings):
            if model.is_byte(i):
                self.bytes[int(s[3:5], 16)] = i
            elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)) and SPACE not in s[1:] and len(s) <= MOST_PIECE:
                self.weight[s] = (i, -power * math.log(i + 1.0))
        self.byte_weight = -power * math.log(n)
        spelt = {x.replace(SPACE, " "): v for x, v in self.weight.items()}
        #: Whether some piece has these two bytes side by side: elsewhere lattices fall apart. Characters are never split.
        self.joined = np.zeros((256, 256), bool)
        for x in spelt:
            raw = np.frombuffer(x.encode(), np.uint8)
            self.joined[raw[:-1], raw[1:]] = True
        self.joined[:, 0x80:0xC0] = True
        self.joined = self.joined.ravel()
        hashes, ids, weights = [], [], []
        for length in range(1, MOST_PIECE + 1):
            heads = list(dict.fromkeys(x[:length] for x in spelt if len(x) >= length))
            points = _code_points("".join(heads)).reshape(-1, length)
            hashes.append((B.mix64(points.astype(np.uint64) + np.uint64(1)) * B.powers(length, _BASE)).sum(axis=1, dtype=np.uint64))
            found = [spelt.get(x, (-1, 0.0)) for x in heads]
            ids.append(np.array([x[0] for x in found], np.int64))
            weights.append(np.array([x[1] for x in found]))
        hashes = np.concatenate(hashes)
        order = np.argsort(hashes)
        self.hashes, self.ids, self.weights = hashes[order], np.concatenate(ids)[order], np.concatenate(weights)[order]
        self.buckets = np.searchsorted(self.hashes >> np.uint64(44), np.arange((1 << 20) + 1, dtype=np.uint64))

    def find(self, h: np.ndarray) -> np.ndarray:
        """Places of these hashes among those of all beginnings of pieces; -1 elsewhere."""
        bucket = (h >> np.uint64(44)).astype(np.int64)
        at, end = self.buckets[bucket], self.buckets[bucket + 1]
        out = np.full(len(h), -1)
        live = np.flatnonzero(at < end)
        while len(live):
            hit = self.hashes[at[live]] == h[live]
            out[live[hit]] = at[live[hit]]
            live = live[~hit]
            at[live] += 1
            live = live[at[live] < end[live]]
        return out

    def ids_of(self, code: int) -> list[int]:
        """The ids of an edge: one piece, or the bytes of a character that has none."""
        return [code] if code >= 0 else [self.bytes[b] for b in chr(-code - 1).encode("utf-8", "surrogatepass")]

    def lattices(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(node, next node, probability given the node, edge code) of all edges, by node, long ones first, and each word's first node; -1 ends a word."""
        text = _code_points("".join(words))
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        roots = np.cumsum(sizes) - sizes
        n = len(text)
        ends = np.repeat(roots + sizes, sizes)
        left = ends - np.arange(n)
        sums = _prefix_sums(text)
        back = B.powers(n + 1, _INVERSE)
        found, at = [], np.arange(n)
        for size in range(1, MOST_PIECE + 1):
            at = at[left[at] >= size]
            place = self.find((sums[at + size] - sums[at]) * back[at])
            at, place = at[place >= 0], place[place >= 0]
            whole = np.flatnonzero(self.ids[place] >= 0)
            src, code, weight = at[whole], self.ids[place[whole]], self.weights[place[whole]]
            if size == 1:
                bare = np.ones(n, bool)
                bare[src] = False
                bare = np.flatnonzero(bare)
                points = text[bare]
                width = 1 + (points >= 0x80) + (points >= 0x800) + (points >= 0x10000)
                src, code, weight = np.append(src, bare), np.append(code, -points - 1), np.append(weight, self.byte_weight * width)
            found.append((src, code, weight))
        each = np.zeros(n, np.int64)
        for src, _, _ in found:
            each[src] += 1
        first = np.cumsum(each) - each
        edges, filled = int(each.sum()), first.copy()
        code, value, dst = np.empty(edges, np.int64), np.empty(edges), np.empty(edges, np.int64)
        for size in range(MOST_PIECE, 0, -1):
            src, codes, weights = found[size - 1]
            to = filled[src]
            code[to], value[to], dst[to] = codes, weights, src + size
            filled[src] += 1
        src = np.repeat(np.arange(n), each)
        final = dst == ends[src]
        mass = np.zeros(n + 1)
        nodes = np.argsort(left.astype(np.uint16) if n and left.max() < 1 << 16 else left, kind="stable")
        counts = each[nodes]
        heads = np.cumsum(counts) - counts
        order = np.repeat(first[nodes] - heads, counts) + np.arange(edges)
        cuts = np.flatnonzero(np.diff(left[nodes], prepend=-1, append=-1))
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            lo, hi = heads[a], heads[b - 1] + counts[b - 1]
            own = order[lo:hi]
            v = value[own] + np.where(final[own], 0.0, mass[dst[own]])
            value[own] = v
            start = heads[a:b] - lo
            top = np.maximum.reduceat(v, start)
            mass[nodes[a:b]] = top + np.log(np.add.reduceat(np.exp(v - np.repeat(top, counts[a:b])), start))
        return src, np.where(final, -1, dst), np.exp(value - mass[src]), code, roots

    def decode(self, ids: list[int]) -> str:
        """The text of a segmentation."""
        value = {i: b for b, i in enumerate(self.bytes)}
        raw = b"".join(bytes([value[i]]) if i in value else self.strings[i].replace(SPACE, " ").encode() for i in ids)
        return raw.decode("utf-8", "surrogatepass")[1:]


def _salted(key, *salts):
    h = key
    for n, s in enumerate(salts):
        h = B.mix64(h * B.GRAM_KEYS[n] + np.asarray(s).astype(np.uint64))
    return h


def _uniform(key: np.ndarray, *salts) -> np.ndarray:
    return ((_salted(key, *salts) >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)


def _gumbel(u):
    return -np.log(-np.log(u))


def _below(value, bound):
    """A Gumbel draw, made to lie below ``bound``."""
    return -np.logaddexp(-bound, -value)


class Lattices:
    """The edges of the words met so far, by node. All are forgotten before they become more than ``most``, but for those of one slice.

    ``cum`` cumulates the probabilities of a node's edges in fixed point; it doesn't depend on what else is held.
    """

    def __init__(self, pieces: Pieces, most: int = MOST_EDGES):
        self.pieces, self.most = pieces, most
        self.forget()

    def forget(self) -> None:
        self.index: dict[bytes, int] = {}
        self.held: dict[str, np.ndarray] = {}
        self.root, self.first, self.src, self.dst, self.code, self.cum, self.prob, self.single = (self._add(*x) for x in (
            ("root", np.zeros(0, np.int64)), ("first", np.zeros(1, np.int64)), ("src", np.zeros(0, np.int32)), ("dst", np.zeros(0, np.int32)),
            ("code", np.zeros(0, np.int32)), ("cum", np.zeros(0, np.int64)), ("prob", np.zeros(0)), ("single", np.zeros(0, bool)),
        ))

    def _add(self, name: str, more: np.ndarray) -> np.ndarray:
        """All values of a column after ``more`` are appended; room grows by doubling."""
        n = len(getattr(self, name)) if name in self.held else 0
        room = self.held.get(name)
        if room is None or n + len(more) > len(room):
            wider = np.empty(max(2 * n, n + len(more)), more.dtype if room is None else room.dtype)
            wider[:n] = room[:n] if n else wider[:0]
            room = self.held[name] = wider
        room[n : n + len(more)] = more
        return room[: n + len(more)]

    def roots(self, words: list[bytes]) -> np.ndarray:
        """The first node of each of these distinct words."""
        if len(self.src) > self.most:
            self.forget()
        index = self.index
        new = [w for w in words if w not in index]
        if new:
            index.update(zip(new, range(len(index), len(index) + len(new)), strict=True))
            src, dst, prob, code, root = self.pieces.lattices([w.decode("utf-8", "surrogatepass") for w in new])
            first = np.append(np.flatnonzero(np.diff(src, prepend=-1)), len(src))
            each = np.diff(first)
            share, at, width = prob.copy(), first[:-1], each
            for r in range(1, int(each.max())):
                at, width = at[width > r], width[width > r]
                share[at + r] += share[at + r - 1]
            share = np.minimum((share * (1 << FRACTION)).astype(np.int64), (1 << FRACTION) - 1)
            share[first[1:] - 1] = (1 << FRACTION) - 1
            base = len(self.first) - 1
            self.first = self._add("first", first[1:] + len(self.src))
            self.root = self._add("root", root + base)
            self.src = self._add("src", src + base)
            self.dst = self._add("dst", np.where(dst < 0, -1, dst + base))
            self.code = self._add("code", code)
            self.cum = self._add("cum", share)
            self.prob = self._add("prob", prob)
            self.single = self._add("single", np.repeat(each == 1, each))
        return self.root[np.fromiter(map(index.__getitem__, words), np.int64, len(words))]


class Search:
    """The searches of the rows of one slice, in step.

    Texts are cut before every space and wherever no piece has the two characters side by side, so most parts
    are short and come again; a draw for a text is one for each part.
    """

    def __init__(self, lattices: Lattices, texts: pa.Array, keys: np.ndarray):
        self.keys = keys
        long = np.flatnonzero(pc.binary_length(texts).to_numpy(zero_copy_only=False) > 0)
        raw, offs = string_buffers(pc.binary_join_element_wise(pa.scalar(" "), texts.take(pa.array(long)), pa.scalar("")))
        starts = np.flatnonzero(~lattices.pieces.joined[(raw[:-1].astype(np.int64) << 8) | raw[1:]]) + 1
        starts = np.append(np.zeros(min(1, len(raw)), np.int64), starts)
        words = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(np.append(starts, len(raw))), pa.py_buffer(np.ascontiguousarray(raw))])
        self.row = long[np.searchsorted(offs, starts, "right") - 1]
        coded = words.dictionary_encode()
        roots = lattices.roots(coded.dictionary.to_pylist())
        self.root = roots[coded.indices.to_numpy(zero_copy_only=False)]
        self.src, self.dst, self.prob, self.code, self.first, self.cum = lattices.src, lattices.dst, lattices.prob, lattices.code, lattices.first, lattices.cum
        self.single = lattices.single
        self.word_first = np.searchsorted(self.row, np.arange(len(texts) + 1))
        self.word_key = _salted(keys[self.row], np.arange(len(self.row)) - self.word_first[self.row])

    def draw(self, nodes: np.ndarray, words: np.ndarray, turn: int) -> tuple[np.ndarray, np.ndarray]:
        """Edges from each node to the end of its word, and the word of each, in order; each word comes once."""
        edges, of, level = [], [], 0
        key = self.word_key[words]
        while len(nodes):
            u = (_salted(key, (turn << 32) + level) >> np.uint64(64 - FRACTION)).astype(np.int64)
            e = self.first[nodes]
            on = np.flatnonzero(self.cum[e] < u)
            while len(on):
                e[on] += 1
                on = on[self.cum[e[on]] < u[on]]
            edges.append(e)
            of.append(words)
            nodes = self.dst[e]
            on = np.flatnonzero(nodes >= 0)
            nodes, words, key, level = nodes[on], words[on], key[on], level + 1
        if not edges:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        all_of = np.concatenate(of)
        each = np.bincount(all_of, minlength=len(self.row))
        place = np.cumsum(each) - each
        out = np.empty(len(all_of), np.int64)
        for n, (e, w) in enumerate(zip(edges, of, strict=True)):
            out[place[w] + n] = e
        return out, np.repeat(np.arange(len(each)), each)

    def run(self, k: int) -> list[list[tuple[np.ndarray, float, float]]]:
        """For each row up to k + 1 (edges, log-probability, perturbed value), best first; the last one's edges may be None."""
        rows = len(self.keys)
        done: list[list] = [[] for _ in range(rows)]
        heaps: list[list] = [[] for _ in range(rows)]
        alive = np.flatnonzero(np.diff(self.word_first)).tolist()
        starts = dict(zip(alive, _gumbel(_uniform(self.keys[alive], 1 << 20)).tolist(), strict=True)) if alive else {}
        tasks = [(row, starts[row], None, 0, (), 0.0) for row in alive]
        for turn in range(k):
            if not tasks:
                break
            nodes, words, heads = [], [], []
            own_keys, steps = self.keys[[t[0] for t in tasks]], np.array([t[3] for t in tasks], np.int64)
            branch, others = _uniform(own_keys, steps, turn, 1 << 21).tolist(), _gumbel(_uniform(own_keys, steps, turn, 1 << 23)).tolist()
            for u, (row, value, base, p, excluded, mass) in zip(branch, tasks, strict=True):
                if base is None:
                    lo, prefix = self.word_first[row], (np.zeros(0, np.int64), np.zeros(0, np.int64))
                else:
                    node = self.src[base[0][p]]
                    own = [e for e in range(self.first[node], self.first[node + 1]) if e not in excluded]
                    share = np.cumsum(self.prob[own])
                    e = own[min(int(np.searchsorted(share, u * share[-1])), len(own) - 1)]
                    w = int(base[1][p])
                    prefix = (np.append(base[0][:p], e), np.append(base[1][:p], w))
                    if self.dst[e] >= 0:
                        nodes.append(self.dst[e : e + 1])
                        words.append(np.array([w]))
                    lo = w + 1
                rest = np.arange(lo, self.word_first[row + 1])
                nodes.append(self.root[rest])
                words.append(rest)
                heads.append(prefix)
            edges, of = self.draw(np.concatenate(nodes), np.concatenate(words), turn)
            ends = np.searchsorted(self.row[of], [t[0] for t in tasks], "right")
            noise_key = _salted(self.keys, turn, 1 << 22)
            following = []
            for t, (row, value, base, p, excluded, mass) in enumerate(tasks):
                a, b = ends[t - 1] if t else 0, ends[t]
                path = np.concatenate([heads[t][0], edges[a:b]])
                at_word = np.concatenate([heads[t][1], of[a:b]])
                prob = self.prob[path]
                log_prob = np.log(np.maximum(prob, 1e-300))
                before = np.cumsum(log_prob)
                done[row].append((path, float(before[-1]), value))
                from_ = 0 if base is None else p + 1
                step = np.arange(from_, len(path))
                step = step[~self.single[path[from_:]]]
                room = (before - log_prob)[step] + np.log(np.maximum(1 - prob[step], 1e-15))
                noise = _gumbel(_uniform(noise_key[row : row + 1], step))
                values = _below(room + noise, value)
                need = k - turn
                best = np.argpartition(-values, need)[:need] if len(values) > need else np.arange(len(values))
                for i in best.tolist():
                    heapq.heappush(heaps[row], (-float(values[i]), turn, int(step[i]), (int(path[step[i]]),)))
                if base is not None:
                    out = (*excluded, int(path[p]))
                    node = self.src[path[p]]
                    left = 1.0 - float(self.prob[list(out)].sum())
                    if len(out) < self.first[node + 1] - self.first[node] and left > 1e-15:
                        prior = float(before[p] - log_prob[p])
                        heapq.heappush(heaps[row], (-float(_below(prior + math.log(left) + others[t], value)), turn, p, out))
                done[row][-1] += (at_word,)
                if heaps[row]:
                    v, t0, p0, x0 = heapq.heappop(heaps[row])
                    source = done[row][t0]
                    following.append((row, -v, (source[0], source[3]), p0, x0, 0.0))
            tasks = following
        for row, value, *_ in tasks:
            done[row].append((None, 0.0, value))
        return done


def _lattices(path: str, power: float) -> Lattices:
    """The vocabulary and the words met; made once in each Python worker."""
    import sentencepiece

    made = sentencepiece.__dict__.setdefault("_lattices_by_path", {})
    if (path, power) not in made:
        made[path, power] = Lattices(Pieces(path, power))
    return made[path, power]


def _sample(path: str, k: int, power: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lattices = _lattices(path, power)
        pieces = lattices.pieces
        for batch in slices(batches, most=SLICE):
            keys = batch.column(1).to_numpy().view(np.uint64)
            search = Search(lattices, batch.column(2), keys)
            out = ([], [], [], [], [], [], [], [])
            for row, found in enumerate(search.run(k)):
                edge = found[k][2] if len(found) > k else -math.inf
                for rank, (path_, log_prob, value, *_) in enumerate(found[:k]):
                    code = search.code[path_]
                    odd = np.flatnonzero(code < 0)
                    ids = code.astype("<u4")
                    if len(odd):
                        parts, at = [], 0
                        for i in odd.tolist():
                            parts += [ids[at:i], np.array(pieces.ids_of(int(code[i])), "<u4")]
                            at = i + 1
                        ids = np.concatenate([*parts, ids[at:]])
                    chance = 1.0 if edge == -math.inf else -math.expm1(-math.exp(min(log_prob - edge, 50.0)))
                    for column, v in zip(out, (row, rank, len(ids), zlib.crc32(ids.tobytes()), log_prob, value, chance, ids.astype(np.int32)), strict=True):
                        column.append(v)
            kinds = (pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64(), pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array(out[0], pa.int64())), *(pa.array(c, t) for c, t in zip(out[1:], kinds, strict=True))],
                ["doc_id", "rank", "n_pieces", "ids_crc32", "log_prob", "perturbed", "inclusion", "ids"],
            )

    return run


def sampled_segmentations(docs: DataFrame, k: int = SAMPLES, model: str | None = None, power: float = RANK_POWER) -> DataFrame:
    """Up to k distinct segmentations of each text of ``docs`` (doc_id, text), a row each.

    doc_id, rank (from 0, by perturbed value), n_pieces, ids_crc32, log_prob, perturbed, inclusion (the chance that a
    sample of this threshold holds it; 1 where a text has no more than k), and ids. Pieces don't cross
    spaces. A space is the mark that begins a word; characters without a piece are spelt in bytes, so that decoding gives the text
    back exactly. Null and empty texts have none. Draws depend on doc_id and text alone, so copies with
    one doc_id are sampled alike; a null doc_id is a key too. No shuffle.
    """
    texts = text_frame(docs, F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("doc_id").alias("key"))
    schema = "doc_id long, rank int, n_pieces long, ids_crc32 long, log_prob double, perturbed double, inclusion double, ids array<int>"
    return texts.mapInArrow(_sample(model or vocabulary_path("piece_bpe_32k.model"), k, power), schema)


def op6_sampled_segmentations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampled_segmentations(table(spark, sf_dir, "documents"))
