"""SentencePiece encoding that samples distinct segmentations, and decoding.

A text's lattice has a node before each character and an edge for each piece of the vocabulary;
pieces of the file are taken as a unigram model whose probabilities follow Zipf's law in the order
of the file. No piece goes on over the beginning of a word, so the lattice is a chain of the words'
lattices, which are built once for each different word of a batch: a trie walks along all
places at once, then all backward sums are made from the words' ends.

Gumbel top-k: give each segmentation its log-probability plus Gumbel noise; the k largest are a
sample without replacement. The search is top-down. The largest value of a set of paths is a Gumbel
variable of the set's total probability, and so an exact bound: sets wait in a queue by it, the best
is taken, a path is drawn in it, and the rest of the set is split by where paths leave
that path. Sets that leave it late wait together until the bound of all of them is the best. The
value of the first path not taken gives the inclusion scores of those taken. All noise comes
from a hash of the row's key.
"""

from __future__ import annotations

import functools
import hashlib
import heapq
import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SAMPLES = 2
SEED = 20
#: How sharply the distribution follows the model; 1 is the model itself.
SHARPNESS = 1.0
#: Places after a branch at which the sets that leave the path wait one by one.
NEAR = 12
#: Characters in a batch.
BATCH_CHARS = 1_500_000
SPACE = "▁"
DENSE = 128
FIRST_BYTE = 3
ODD = (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB)
MASK = (1 << 64) - 1


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(ODD[1])
    x = (x ^ (x >> np.uint64(27))) * np.uint64(ODD[2])
    return x ^ (x >> np.uint64(31))


def mix_one(x: int) -> int:
    x = ((x ^ (x >> 30)) * ODD[1]) & MASK
    x = ((x ^ (x >> 27)) * ODD[2]) & MASK
    return x ^ (x >> 31)


class Vocabulary:
    """Pieces, their weights, and a trie whose edges of the commonest symbols lie in a dense table."""

    def __init__(self, pieces: list[str], n_special: int = FIRST_BYTE + 256, sharpness: float = SHARPNESS):
        self.pieces = pieces
        norm = math.log(sum(1 / r for r in range(1, len(pieces) - n_special + 2)))
        self.weight = np.array([-sharpness * (math.log(max(i - n_special, 0) + 1) + norm) for i in range(len(pieces))])
        self.byte_weight = float(self.weight[-1])
        self.bytes = [bytes([i - FIRST_BYTE]) if FIRST_BYTE <= i < n_special else b"" if i < FIRST_BYTE else p.replace(SPACE, " ").encode() for i, p in enumerate(pieces)]
        self.byte_table = np.array([*self.bytes, None], object)[:-1]
        counts: dict[str, int] = {}
        for p in pieces[n_special:]:
            for c in p:
                counts[c] = counts.get(c, 0) + 1
        symbol = {c: i for i, c in enumerate(sorted(counts, key=lambda c: (-counts[c], c)), 1)}
        self.symbol_of = np.zeros(0x110000, np.int32)
        for c, i in symbol.items():
            self.symbol_of[ord(c)] = i
        self.symbol_of[ord(" ")] = symbol.get(SPACE, 0)
        self.symbol_of[ord(SPACE)] = 0  # in a text it is spelt in bytes, so that decoding gives it back
        children: dict[tuple[int, int], int] = {}
        piece_at = [-1]
        for i, p in enumerate(pieces[n_special:], n_special):
            node = 0
            for c in p:
                key = (node, symbol[c])
                if key not in children:
                    children[key] = len(piece_at)
                    piece_at.append(-1)
                node = children[key]
            piece_at[node] = i
        self.piece_at, self.longest = np.array(piece_at, np.int32), max((len(p) for p in pieces[n_special:]), default=1)
        self.dense = np.zeros((len(piece_at), DENSE), np.int32)
        rare = []
        for (node, s), child in children.items():
            if s < DENSE:
                self.dense[node, s] = child
            else:
                rare.append((node * 65536 + s, child))
        rare.sort()
        self.rare_key = np.array([k for k, _ in rare] or [-1], np.int64)
        self.rare_child = np.array([c for _, c in rare] or [0], np.int32)

    def step(self, node: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        low = symbol < DENSE
        if low.all():
            return self.dense[node, symbol]
        out = np.zeros(len(node), np.int32)
        out[low] = self.dense[node[low], symbol[low]]
        high = np.flatnonzero(~low)
        key = node[high].astype(np.int64) * 65536 + symbol[high]
        at = np.minimum(np.searchsorted(self.rare_key, key), len(self.rare_key) - 1)
        out[high] = np.where(self.rare_key[at] == key, self.rare_child[at], 0)
        return out

    def spelt(self, codes: np.ndarray) -> np.ndarray:
        """Piece ids; a negative code is a character in bytes."""
        if not len(codes) or codes.min() >= 0:
            return codes
        out = []
        for c in codes.tolist():
            if c >= 0:
                out.append(c)
            else:
                out += [FIRST_BYTE + b for b in chr(-c).encode("utf-8", "surrogatepass")]
        return np.array(out, np.int32)


@functools.cache
def vocabulary(path: str) -> Vocabulary:
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    return Vocabulary([model.id_to_piece(i) for i in range(model.get_piece_size())])


def decode(vocab: Vocabulary, ids: np.ndarray | list[int]) -> bytes:
    """The UTF-8 text of the pieces, without the space put before the first word."""
    return b"".join(vocab.byte_table[np.asarray(ids, np.int64)].tolist())[1:]


def units_of(text: str) -> list[str]:
    """Words with the spaces before them, less the one space that each has at least."""
    if "  " not in text and text[-1] != " ":
        return text.split(" ") if text[0] != " " else [u[1:] for u in re.findall(" *[^ ]+", " " + text)]
    return [u[1:] for u in re.findall(" *[^ ]+| +$", " " + text)]


class Lattice:
    """Lattices of words, one after another; ``cum`` has the probabilities of a node's edges, summed."""

    def __init__(self, vocab: Vocabulary, words: list[str]):
        cp = np.frombuffer((" " + " ".join(words)).encode("utf-32-le", "surrogatepass"), np.uint32)
        symbols = vocab.symbol_of[cp]
        sizes = np.fromiter(map(len, words), np.int64, len(words)) + 1
        self.end = np.cumsum(sizes)
        self.start = self.end - sizes
        n = len(cp)
        stop = np.repeat(self.end, sizes)
        place, node, found = np.arange(n), np.zeros(n, np.int32), []
        for length in range(1, vocab.longest + 1):
            at = place + (length - 1)
            ok = at < stop[place]
            place, node, at = place[ok], node[ok], at[ok]
            node = vocab.step(node, symbols[at])
            ok = node > 0
            place, node = place[ok], node[ok]
            if not len(place):
                break
            piece = vocab.piece_at[node]
            has = piece >= 0
            found.append((place[has], length, piece[has]))
        lost = np.flatnonzero(symbols == 0)
        degree = np.bincount(lost, minlength=n)
        for place, _, _ in found:
            degree[place] += 1
        left = stop - np.arange(n)
        order = np.argsort(left.astype(np.uint16) if len(left) and left.max() < 65536 else left, kind="stable")
        first = np.concatenate([[0], np.cumsum(degree[order])])
        self.off = np.empty(n, np.int64)
        self.off[order] = first[:-1]
        self.degree = degree
        total = int(first[-1])
        self.next, self.code, weight = np.empty(total, np.int64), np.empty(total, np.int32), np.empty(total)
        fill = self.off.copy()
        for place, length, piece in reversed(found):  # long pieces first: a draw mostly stops there
            at = fill[place]
            self.next[at], self.code[at], weight[at] = place + length, piece, vocab.weight[piece]
            fill[place] += 1
        at = fill[lost]
        c = cp[lost].astype(np.int64)
        n_bytes = 1 + (c > 0x7F) + (c > 0x7FF) + (c > 0xFFFF)
        self.next[at], self.code[at], weight[at] = lost + 1, np.where(n_bytes == 1, FIRST_BYTE + c, -c), n_bytes * vocab.byte_weight
        back = np.zeros(n + 1)
        inner = np.zeros(total)
        ends = np.zeros(n + 1, bool)
        ends[self.end] = True
        bounds = np.concatenate([[0], np.cumsum(np.bincount(left, minlength=1)[1:])])
        self.lp = weight
        for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            if a == b:
                continue
            e0, e1 = int(first[a]), int(first[b])
            onward = self.next[e0:e1]
            value = weight[e0:e1] + np.where(ends[onward], 0.0, back[onward])
            sums = np.logaddexp.reduceat(value, first[a:b] - e0)
            back[order[a:b]] = sums
            inner[e0:e1] = value - np.repeat(sums, degree[order[a:b]])
        self.lp = inner
        self.cum = np.exp(inner)  # summed edge by edge in each node, so that rounding does not depend on the other texts
        more, edges, k = first[:-1], degree[order], 1
        while len(more := more[edges > k]):
            edges = edges[edges > k]
            self.cum[more + k] += self.cum[more + k - 1]
            k += 1
        self.cum[first[1:] - 1] = 2.0
        self.source = np.repeat(order, degree[order])

    def walk(self, at: np.ndarray, end: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Draws a path from each node to its end: the edges of all, and how many each has."""
        counts, steps, step = np.zeros(len(at), np.int64), [], 0
        live = np.flatnonzero(at < end)
        at, end, keys = at[live], end[live], keys[live]
        with np.errstate(over="ignore"):
            while len(live):
                u = (mix(keys + np.uint64((step * ODD[0]) & MASK)) >> np.uint64(11)) * 2.0**-53
                edge = self.off[at]
                more = np.flatnonzero(u >= self.cum[edge])
                while len(more):
                    edge[more] += 1
                    more = more[u[more] >= self.cum[edge[more]]]
                steps.append((live, edge))
                counts[live] += 1
                at = self.next[edge]
                on = np.flatnonzero(at < end)
                live, at, end, keys = live[on], at[on], end[on], keys[on]
                step += 1
        first = np.cumsum(counts) - counts
        out = np.empty(int(counts.sum()), np.int64)
        for step, (live, edge) in enumerate(steps):
            out[first[live] + step] = edge
        return out, counts


class Search:
    """The queue of one text's path sets."""

    def __init__(self, lattice: Lattice, key: int, near: int):
        self.lattice, self.key, self.near, self.n = lattice, key, near, 0
        self.queue: list[tuple] = []
        self.paths: list[tuple] = []  # edges, edges of each word, log-probability, perturbed value

    def uniform(self) -> float:
        self.n += 1
        return ((mix_one((self.key + self.n * ODD[0]) & MASK) >> 11) + 0.5) * 2.0**-53

    def below(self, mass: float, top: float) -> float:
        """A Gumbel variable of log-mass ``mass``, given that it is at most ``top``."""
        return -float(np.logaddexp(-top, math.log(-math.log(self.uniform())) - mass))

    def first(self) -> float:
        return -math.log(-math.log(self.uniform()))

    def accept(self, edges: np.ndarray, counts: np.ndarray, log_prob: float, value: float, branch: int, barred: tuple) -> None:
        self.paths.append((edges, counts, log_prob, value))
        before = float(self.lattice.lp[edges[:branch]].sum())
        for mass, what in self.leaving(len(self.paths) - 1, branch, before, barred):
            heapq.heappush(self.queue, (-self.below(mass, value), self.n, what))

    def leaving(self, path: int, at: int, before: float, barred: tuple) -> list[tuple]:
        """(log-mass, set) of the paths that leave ``path`` at a place from ``at`` on."""
        lat, (edges, _, log_prob, _), out = self.lattice, self.paths[path], []
        near = edges[at : at + self.near].tolist()
        for i, (edge, lp) in enumerate(zip(near, lat.lp[near].tolist(), strict=True), at):
            node = int(lat.source[edge])
            if lat.degree[node] > 1:
                gone = (edge, *barred) if i == at else (edge,)
                if len(gone) == 1:
                    rest = -math.expm1(lp)
                else:
                    rest = sum(math.exp(lat.lp[e]) for e in range(lat.off[node], lat.off[node] + lat.degree[node]) if e not in gone)
                if rest > 0:
                    out.append((before + math.log(rest), (path, i, before, gone)))
            before += lp
        if at + self.near < len(edges) and log_prob < before:
            out.append((before + math.log(-math.expm1(log_prob - before)), (path, at + self.near, before, None)))
        return out

    def pop(self) -> tuple | None:
        """The best set that leaves one path at one place: (value, path, place, barred edges)."""
        while self.queue:
            value, _, (path, at, before, gone) = heapq.heappop(self.queue)
            value = -value
            if gone is not None:
                return value, path, at, gone
            parts = self.leaving(path, at, before, ())
            top, draw = max((m for m, _ in parts), default=0.0), self.uniform()
            draw *= sum(math.exp(m - top) for m, _ in parts)
            chosen = len(parts) - 1
            for i, (mass, _) in enumerate(parts):
                draw -= math.exp(mass - top)
                if draw < 0:
                    chosen = i
                    break
            for i, (mass, what) in enumerate(parts):  # one of them has the value of the whole, the others less
                heapq.heappush(self.queue, (-(value if i == chosen else self.below(mass, value)), self.n, what))
        return None

    def bound(self) -> float:
        return -self.queue[0][0] if self.queue else -math.inf


def sample(vocab: Vocabulary, texts: list[str], seeds: list[int], samples: int, near: int = NEAR) -> list[list[tuple]]:
    """For each text up to ``samples`` distinct (ids, log-probability, perturbed value, inclusion score)."""
    words: dict[str, int] = {}
    unit: list[int] = []
    n_units = []
    for text in texts:
        own = units_of(text) if text else []
        unit += [words.setdefault(w, len(words)) for w in own]
        n_units.append(len(own))
    lat = Lattice(vocab, list(words)) if words else None
    units, sizes = np.array(unit, np.int64), np.array(n_units)
    firsts = np.cumsum(sizes) - sizes
    hashed = np.array([mix_one((s & MASK) ^ SEED) for s in seeds], np.uint64)
    searches = [Search(lat, mix_one(int(h) ^ ODD[0]), near) for h in hashed]
    for round_no in range(samples):
        todo, spans, start = [], [], []
        for d, search in enumerate(searches):
            if not n_units[d]:
                continue
            if not round_no:
                todo.append((d, search.first(), 0, 0, (), None))
                spans.append((firsts[d], firsts[d] + n_units[d]))
                start.append(lat.start[units[firsts[d]]])
            elif best := search.pop():
                value, path, at, gone = best
                edges, counts = search.paths[path][:2]
                word = int(np.searchsorted(np.cumsum(counts), at, side="right"))
                node = int(lat.source[edges[at]])
                open_edges = [e for e in range(lat.off[node], lat.off[node] + lat.degree[node]) if e not in gone]
                draw = search.uniform() * sum(math.exp(lat.lp[e]) for e in open_edges)
                edge = open_edges[-1]
                for e in open_edges:
                    draw -= math.exp(lat.lp[e])
                    if draw < 0:
                        edge = e
                        break
                todo.append((d, value, path, at, gone, (word, edge)))
                spans.append((firsts[d] + word, firsts[d] + n_units[d]))
                start.append(lat.next[edge])
        if not todo:
            break
        lengths = np.array([b - a for a, b in spans])
        where = np.repeat(np.array([a for a, _ in spans]) - (np.cumsum(lengths) - lengths), lengths) + np.arange(lengths.sum())
        at = lat.start[units[where]]
        at[np.cumsum(lengths) - lengths] = start
        doc = np.repeat([t[0] for t in todo], lengths)
        with np.errstate(over="ignore"):
            keys = mix(hashed[doc] + (where - firsts[doc]).astype(np.uint64) * np.uint64(ODD[1]) + np.uint64(round_no + 1))
        drawn, n_drawn = lat.walk(at, lat.end[units[where]], keys)
        unit_at = np.concatenate([[0], np.cumsum(lengths)])
        edge_at = np.concatenate([[0], np.cumsum(n_drawn)])[unit_at]
        for i, (d, value, path, place, gone, step) in enumerate(todo):
            edges, counts = drawn[edge_at[i] : edge_at[i + 1]], n_drawn[unit_at[i] : unit_at[i + 1]]
            if step:
                old_edges, old_counts = searches[d].paths[path][:2]
                word, edge = step
                edges = np.concatenate([old_edges[:place], [edge], edges])
                head = place - int(old_counts[:word].sum()) + 1
                counts = np.concatenate([old_counts[:word], [head + counts[0]], counts[1:]])
            searches[d].accept(edges, counts, float(lat.lp[edges].sum()), value, place, gone)
    out = []
    for d, search in enumerate(searches):
        if not n_units[d]:
            out.append([(np.empty(0, np.int32), 0.0, 0.0, 1.0)])  # the one segmentation of the empty text
            continue
        bound = search.bound()
        rows = []
        for edges, _, log_prob, value in search.paths:
            ids = vocab.spelt(lat.code[edges])
            score = 1.0 if bound == -math.inf else -math.expm1(-math.exp(min(log_prob - bound, 50.0)))
            rows.append((ids, log_prob, value, score))
        out.append(rows)
    return out


OUTPUT = "doc_id long, sample_no int, n_pieces long, ids_sha256 string, log_prob double, perturbed double, inclusion double, decoded_sha256 string"


def _sample(path: str, samples: int, with_ids: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab = vocabulary(path)
        kinds = [pa.int64(), pa.int32(), pa.int64(), pa.string(), pa.float64(), pa.float64(), pa.float64(), pa.string(), pa.list_(pa.int32())]
        names = ["doc_id", "sample_no", "n_pieces", "ids_sha256", "log_prob", "perturbed", "inclusion", "decoded_sha256", "ids"]
        width = len(names) if with_ids else len(names) - 1

        def made(docs, texts, seeds):
            columns: list[list] = [[] for _ in range(width)]
            for doc, rows in zip(docs, sample(vocab, texts, seeds, samples), strict=True):
                for no, (ids, log_prob, value, score) in enumerate(rows, 1):
                    row = (doc, no, len(ids), hashlib.sha256(ids.astype("<i4", copy=False).tobytes()).hexdigest(), log_prob, value, score, hashlib.sha256(decode(vocab, ids)).hexdigest(), ids)
                    for column, v in zip(columns, row, strict=False):
                        column.append(v)
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=False)], names=names[:width])

        docs, texts, seeds, held = [], [], [], 0
        for batch in batches:
            for doc, text, seed in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), strict=True):
                docs.append(doc)
                texts.append(text.as_py() or "")
                seeds.append(seed)
                held += len(texts[-1])
                if held >= BATCH_CHARS:
                    yield made(docs, texts, seeds)
                    docs, texts, seeds, held = [], [], [], 0
        if docs:
            yield made(docs, texts, seeds)

    return run


def sampled_encodings(docs: DataFrame, samples: int = SAMPLES, model: str = MODEL, with_ids: bool = False) -> DataFrame:
    """Rows (doc_id, sample_no from 1) with n_pieces, ids_sha256 (32-bit little-endian ids), log_prob,
    perturbed, inclusion and decoded_sha256 (of the decoded UTF-8 text); with_ids adds the ids.

    A text with fewer segmentations than ``samples`` gives all it has; null and empty texts have one,
    without pieces. The key of a row is its doc_id, so rows repeated with one id and text are alike;
    a null id is a key too; an empty table gives none; other columns are ignored.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.xxhash64(F.col("doc_id").cast("string"), F.lit(SEED)).alias("seed"))
    return rows.mapInArrow(_sample(model, samples, with_ids), OUTPUT + (", ids array<int>" if with_ids else ""))
