"""SentencePiece encoding, decoding, and sampled segmentations without replacement.

``encode`` and ``decode`` are the library's. ``sample_segmentations`` draws the k segmentations of
largest perturbed score: Gumbel top-k, found by a perturbed A-star search over the lattice of
pieces. A node of the search is a place in the lattice together with what was chosen before it
and which edges are ruled out there; its bound is a Gumbel variable with the node's total mass
as location, truncated at its parent's. Expanding the best node completes one segmentation: the best
child inherits the bound, its choice is a draw from the node's edges, and every other child along
the way goes back to the queue as one node per place (all edges but the chosen one). The
(k+1)-th bound is the threshold of the inclusion scores. Everything is done for a slice of
documents at a time on flat arrays; a lattice is built once for each distinct word, as no
piece reaches across a word start, and kept for the next slices of the process (``Words``).

Piece probabilities: the vocabulary file holds merge ranks, no probabilities, so a piece of rank r weighs
1 / (r + 10), raised to ``alpha``; a character outside the vocabulary falls back to its bytes, which weigh
1 / 200,000 each. Draws depend on the row key, the seed and the place alone, not on batches or partitions.

Defined results: null and empty texts have the one empty segmentation with probability 1; rows of
equal keys and texts draw equal samples (a null key counts as a key); a text with fewer than k segmentations
returns them all, with inclusion 1; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rpqframe.llm.common import pick, text_slices
from rpqframe.llm.token_count import MARK, model_file, processor

SAMPLES = 2
SLICE = 3 << 18
LONG_WORD = 100
#: Edges (some 35 bytes each) of the words that are kept; what later slices add goes with each of them.
KNOWN_EDGES = 5 << 20
U64 = np.uint64
MIX = U64(0x9E3779B97F4A7C15)
BASE = U64(0xD6E8FEB86659FD93)
FIRST_RANKED = 259  # unknown, begin, end and the 256 bytes come first


def encode(texts: list[str], model_path: str | None = None) -> list[list[int]]:
    return processor(model_file(model_path)).encode(texts, num_threads=1)


def decode(ids: list[list[int]], model_path: str | None = None) -> list[str]:
    return processor(model_file(model_path)).decode(ids)


def encode_texts(docs: DataFrame, text_col: str = "text", out_col: str = "ids", model_path: str | None = None) -> DataFrame:
    """The rows with the library's ids of their whole texts; null texts have null ids. A column ``out_col`` of the input is replaced."""
    src = docs.drop(out_col).withColumn(out_col, F.lit(None).cast("array<int>"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sp = processor(model_file(model_path))
        for batch in batches:
            for rows, texts in text_slices(batch, text_col):
                ids = [None if t is None else sp.encode(t) for t in texts]
                yield pa.RecordBatch.from_arrays([*rows.columns[:-1], pa.array(ids, pa.list_(pa.int32()))], names=rows.schema.names)

    return src.mapInArrow(run, src.schema)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambler of 64-bit integers."""
    x = (x ^ (x >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U64(27))) * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def uniform(x: np.ndarray) -> np.ndarray:
    """Draws in (0, 1) from counters."""
    return ((mix(x) >> U64(11)).astype(np.float64) + 0.5) * 2.0**-53


@lru_cache(maxsize=1)
def _scrambled_low() -> np.ndarray:
    return mix((np.arange(1 << 16, dtype=U64) + U64(1)) * MIX)  # no code point may hash to zero


def scrambled(codes: np.ndarray) -> np.ndarray:
    """A random 64-bit integer for each code point."""
    out = _scrambled_low()[np.minimum(codes, 0xFFFF)]
    high = codes > 0xFFFF
    if high.any():
        out[high] = mix((codes[high].astype(U64) + U64(1)) * MIX)
    return out


def _powers(base: U64, n: int) -> np.ndarray:
    out = np.full(n, base, dtype=U64)
    out[0] = 1
    return np.multiply.accumulate(out)


INVERSE = U64(pow(int(BASE), -1, 1 << 64))


class Vocabulary:
    """Hashes of all pieces and their prefixes in an open table; piece texts in flat arrays."""

    def __init__(self, path: str, alpha: float):
        sp = processor(path)
        self.size = sp.vocab_size()
        pieces = [sp.id_to_piece(i) for i in range(self.size)]
        use = [i for i in range(self.size) if i >= FIRST_RANKED and not (sp.is_control(i) or sp.is_unused(i) or sp.is_byte(i) or sp.is_unknown(i))]
        if any(MARK in pieces[i].lstrip(MARK) for i in use):
            raise ValueError("a piece reaches across a word start")
        self.byte_id = np.array([sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)], dtype=np.int32)
        self.longest = max(len(pieces[i]) for i in use)
        self.log_weight = np.full(self.size, alpha * -np.log(200_000.0))
        self.log_weight[use] = alpha * -np.log(np.array(use) - FIRST_RANKED + 10.0)
        self.raw = [p.replace(MARK, " ").encode() for p in pieces]
        for b, i in enumerate(self.byte_id):
            self.raw[i] = bytes([b])
        self.raw_len = np.array([len(r) for r in self.raw], dtype=np.int64)
        self.raw_at = np.concatenate([[0], np.cumsum(self.raw_len)[:-1]])
        self.raw_flat = np.frombuffer(b"".join(self.raw), dtype=np.uint8)
        table: dict[int, int] = {}
        for i in use:
            h = 0
            for k, ch in enumerate(pieces[i]):
                h = (h + int(scrambled(np.array([ord(ch)], dtype=np.uint32))[0]) * pow(int(BASE), k, 1 << 64)) % (1 << 64)
                table.setdefault(h, -1)
            table[h] = i
        self.words = Words()
        self.bits = max(18, (4 * len(table)).bit_length())
        self.keys, self.vals = np.zeros(1 << self.bits, dtype=U64), np.full(1 << self.bits, -2, dtype=np.int32)
        for h, i in table.items():
            at = int(self._slot(np.array([h], dtype=U64))[0])
            while self.keys[at]:
                at = (at + 1) & ((1 << self.bits) - 1)
            self.keys[at], self.vals[at] = h, i

    def _slot(self, h: np.ndarray) -> np.ndarray:
        return ((h * MIX) >> U64(64 - self.bits)).astype(np.int64)

    def find(self, h: np.ndarray) -> np.ndarray:
        """Piece id, -1 for a mere prefix of pieces, -2 for neither."""
        at = self._slot(h)
        out = np.full(len(h), -2, dtype=np.int32)
        todo = np.arange(len(h))
        while len(todo):
            k = self.keys[at]
            hit = k == h[todo]
            out[todo[hit]] = self.vals[at[hit]]
            go = ~hit & (k != 0)
            todo, at = todo[go], (at[go] + 1) & ((1 << self.bits) - 1)
        return out


@lru_cache(maxsize=2)
def vocabulary(path: str, alpha: float) -> Vocabulary:
    return Vocabulary(path, alpha)


class Lattice:
    """The lattices of all distinct words of a slice, edges by node, long pieces first."""

    def __init__(self, vocab: Vocabulary, codes: np.ndarray, pre: np.ndarray, inv: np.ndarray, starts: np.ndarray, sizes: np.ndarray):
        # codes, pre: all characters and their running hash; starts, sizes: the distinct words' places
        n = int(sizes.sum())
        base = np.concatenate([[0], np.cumsum(sizes)])
        word = np.repeat(np.arange(len(sizes)), sizes)
        at = np.arange(n) - base[word]
        here = starts[word] + at
        self.root = base[:-1] + np.arange(len(sizes))  # a word of n characters has n + 1 nodes
        node = np.arange(n) + word
        left = sizes[word] - at
        live, found, lone = np.arange(n), [], np.zeros(0, dtype=np.int64)
        for size in range(1, vocab.longest + 1):
            live = live[left[live] >= size]
            if not len(live):
                break
            g = here[live]
            ids = vocab.find((pre[g + size] - pre[g]) * inv[g])
            hit = ids >= 0
            found.append((size, live[hit], ids[hit], vocab.log_weight[ids[hit]]))
            if size == 1:
                lone = live[~hit]
            live = live[ids > -2]
        # characters outside the vocabulary: one edge of their bytes; beyond one byte noted as -1 - code point
        code = codes[here[lone]].astype(np.int64)
        n_bytes = 1 + (code > 0x7F) + (code > 0x7FF) + (code > 0xFFFF)
        lone_id = np.where(code < 0x80, vocab.byte_id[np.minimum(code, 0x7F)], -1 - code).astype(np.int32)
        found.insert(0, (1, lone, lone_id, n_bytes * vocab.log_weight[vocab.byte_id[0]]))
        n_nodes = n + len(sizes)
        many = np.zeros(n_nodes + 1, dtype=np.int64)
        for _, frm, _, _ in found:
            many[node[frm] + 1] += 1
        self.first = np.cumsum(many)
        total = int(self.first[-1])
        self.len, self.id, self.end, w = np.empty(total, np.int32), np.empty(total, np.int32), np.empty(total, np.int32), np.empty(total)
        fill = self.first[:-1].copy()
        for size, frm, ids, weight in reversed(found):  # long pieces, mostly the likelier ones, come first
            start = node[frm]
            at_edge = fill[start]
            fill[start] += 1
            self.len[at_edge], self.id[at_edge], self.end[at_edge], w[at_edge] = size, ids, start + size, weight
        log_z = self._backward(node, left, sizes[word], w)
        self.log_q = w + log_z[self.end] - np.repeat(log_z, np.diff(self.first))
        self.q = np.exp(self.log_q)
        # what the other edges of an edge's node weigh: nothing beside a lone edge
        siblings = np.diff(self.first)
        self.others = np.where(np.repeat(siblings == 1, siblings), 0.0, np.maximum(1.0 - self.q, 0.0)).astype(np.float32)
        self.is_end = np.zeros(n_nodes, dtype=bool)
        self.is_end[base[1:] + np.arange(len(sizes))] = True

    def _backward(self, node: np.ndarray, left: np.ndarray, size: np.ndarray, w: np.ndarray) -> np.ndarray:
        """Log of the total weight from each node to its word's end.

        Short words: sums scaled by a constant for each character, which stay in range.
        """
        scale = 7.0
        log_z = np.zeros(len(self.first) - 1)
        for short in (True, False):
            own = np.flatnonzero((size <= LONG_WORD) == short)
            if not len(own):
                continue
            r = left[own]
            own = own[np.argsort(r.astype(np.uint16) if int(r.max()) < 1 << 16 else r, kind="stable")]
            nodes, r = node[own], left[own]
            many = self.first[nodes + 1] - self.first[nodes]
            at = np.concatenate([[0], np.cumsum(many)])
            edge = np.repeat(self.first[nodes] - at[:-1], many) + np.arange(at[-1])
            end = self.end[edge]
            val = np.exp(w[edge] + scale * self.len[edge]) if short else w[edge]
            z = np.ones(len(log_z)) if short else log_z
            cuts = np.searchsorted(r, np.arange(1, int(r[-1]) + 2))
            for a, b in zip(cuts[:-1], cuts[1:]):
                if a == b:
                    continue
                e = slice(at[a], at[b])
                groups = at[a:b] - at[a]
                if short:
                    z[nodes[a:b]] = np.add.reduceat(val[e] * z[end[e]], groups)
                else:
                    x = val[e] + z[end[e]]
                    top = np.maximum.reduceat(x, groups)
                    z[nodes[a:b]] = top + np.log(np.add.reduceat(np.exp(x - np.repeat(top, many[a:b])), groups))
            if short:
                log_z[nodes] = np.log(z[nodes]) - scale * r
        return log_z


class Words:
    """The lattices, and the library's ids, of words met before, in arrays that grow at their ends.

    The words of the first slices stay, up to ``KNOWN_EDGES``; those of a later slice are gone, and written over, when the next one begins.
    """

    KINDS = {"first": np.int64, "len": np.int16, "id": np.int32, "end": np.int32, "log_q": np.float64, "q": np.float64, "others": np.float32, "is_end": bool, "root": np.int64, "ids": np.int32, "ids_at": np.int64, "n_ids": np.int64}

    def __init__(self):
        self.known: dict[int, int] = {}
        self._room: dict[str, np.ndarray] = {}
        for name, kind in self.KINDS.items():
            setattr(self, name, np.zeros(0, dtype=kind))
        self._add("first", np.zeros(1, dtype=np.int64))
        self.mark = {name: len(getattr(self, name)) for name in self.KINDS}
        self.later: list[int] = []

    def begin(self) -> None:
        """A slice begins: what was added last stays where there is room."""
        if len(self.end) <= KNOWN_EDGES:
            self.mark = {name: len(getattr(self, name)) for name in self.KINDS}
        else:
            for name, n in self.mark.items():
                setattr(self, name, getattr(self, name)[:n])
            for h in self.later:
                del self.known[h]
            self.ids_at[self.ids_at >= len(self.ids)] = -1
        self.later = []

    def _add(self, name: str, more: np.ndarray) -> None:
        old = getattr(self, name)
        n = len(old) + len(more)
        room = self._room.get(name, old)
        if n > len(room):
            room = np.empty(max(2 * n, 1 << 12), dtype=old.dtype)
            room[: len(old)] = old
            self._room[name] = room
        room[len(old) : n] = more
        setattr(self, name, room[:n])

    def places(self, vocab: Vocabulary, hashes: np.ndarray, codes: np.ndarray, pre: np.ndarray, inv: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """The number of each word by its hash; lattices are made for those not met before."""
        get = self.known.get
        at = np.array([get(h, -1) for h in hashes.tolist()], dtype=np.int64)
        new = np.flatnonzero(at < 0)
        if len(new):
            part = Lattice(vocab, codes, pre, inv, starts[new], sizes[new])
            at[new] = np.arange(len(new)) + len(self.known)
            self.later = hashes[new].tolist()
            self.known.update(zip(self.later, at[new].tolist()))
            nodes, edges = len(self.is_end), len(self.end)
            self._add("first", part.first[1:] + edges)
            self._add("end", part.end + nodes)
            self._add("root", part.root + nodes)
            for name in ("len", "id", "log_q", "q", "others", "is_end"):
                self._add(name, getattr(part, name))
            self._add("ids_at", np.full(len(new), -1))
            self._add("n_ids", np.zeros(len(new), dtype=np.int64))
        return at

    def encode(self, sp, places: np.ndarray, text: str, starts: np.ndarray, ends: np.ndarray) -> None:
        """Have the ids of the words at these places; ``starts`` and ``ends`` are theirs in the text."""
        new = np.flatnonzero(self.ids_at[places] < 0)
        # the library puts the first mark of a word in front itself, but not where nothing follows
        ids = sp.encode([text[a + 1 : b] for a, b in zip(starts[new].tolist(), ends[new].tolist())], num_threads=1) if len(new) else []
        for k in np.flatnonzero(ends[new] - starts[new] == 1):
            ids[k] = sp.encode("x" + MARK)[len(sp.encode("x")) :]
        size = np.array([len(i) for i in ids], dtype=np.int64)
        self.ids_at[places[new]] = len(self.ids) + np.cumsum(size) - size
        self.n_ids[places[new]] = size
        self._add("ids", np.array(list(chain.from_iterable(ids)), dtype=np.int32))

    def draw(self, node: np.ndarray, u: np.ndarray) -> np.ndarray:
        """An edge of each node by its probability."""
        edge, last = self.first[node], self.first[node + 1] - 1
        out = edge.copy()
        todo = np.arange(len(node))
        while len(todo):
            p = self.q[out[todo]]
            more = (u[todo] >= p) & (out[todo] < last[todo])
            u[todo] -= p
            todo = todo[more]
            out[todo] += 1
        return out


@lru_cache(maxsize=1)
def _all_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    return _powers(BASE, n), _powers(INVERSE, n)


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    pw, inv = _all_tables(max(1 << 20, 1 << n.bit_length()))
    return pw[:n], inv[:n]


def truncated(location: np.ndarray, bound: np.ndarray, u: np.ndarray) -> np.ndarray:
    """Gumbel variables with the given log mass, truncated at the bound."""
    out = np.full(len(location), -np.inf)
    ok = location > -np.inf
    out[ok] = -np.logaddexp(-bound[ok], np.log(-np.log(u[ok])) - location[ok])
    return out


class Slice:
    """Gumbel top-k over the lattices of a slice of documents; it is done with before the next slice of its vocabulary is made."""

    def __init__(self, vocab: Vocabulary, texts: list[str], keys: np.ndarray):
        self.vocab, self.keys, self.n = vocab, keys, len(texts)
        self.texts, self.marked = texts, [(MARK + t.replace(" ", MARK)) if t else "" for t in texts]
        marked = self.marked
        self.codes = np.frombuffer("".join(marked).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        self.doc_at = np.concatenate([[0], np.cumsum([len(m) for m in marked])])
        mark = self.codes == ord(MARK)
        head = mark.copy()
        head[1:] &= ~mark[:-1]
        head[self.doc_at[:-1][np.diff(self.doc_at) > 0]] = True
        starts = np.flatnonzero(head)
        sizes = np.diff(np.append(starts, len(self.codes)))
        pw, inv = _tables(len(self.codes) + 1)
        pre = np.zeros(len(self.codes) + 1, dtype=U64)
        np.cumsum(scrambled(self.codes) * pw[: len(self.codes)], out=pre[1:])
        h = (pre[starts + sizes] - pre[starts]) * inv[starts] + sizes.astype(U64) * MIX
        which, distinct = pd.factorize(h)
        rep = np.zeros(len(distinct), dtype=np.int64)
        rep[which] = np.arange(len(which))
        vocab.words.begin()
        self.lat = vocab.words if len(starts) else None
        self.starts, self.ends = starts[rep], starts[rep] + sizes[rep]
        self.places = vocab.words.places(vocab, distinct, self.codes, pre, inv, starts[rep], sizes[rep]) if len(starts) else rep
        self.occ_word = self.places[which]
        self.occ_root = vocab.words.root[self.occ_word]
        self.occ_at = np.searchsorted(starts, self.doc_at)
        self.occ_doc = np.repeat(np.arange(self.n), np.diff(self.occ_at))

    def encoded(self, sp) -> list[np.ndarray]:
        """The library's ids of each whole text, from one encoding of each distinct word.

        No piece reaches across a word start (checked when the vocabulary is loaded) and merges only ever build pieces,
        so a text's ids are those of its words in order. A text that the library changes before it encodes goes to it whole.
        """
        if self.lat is None:
            return [np.zeros(0, dtype=np.int32) for _ in self.texts]
        self.lat.encode(sp, self.places, "".join(self.marked), self.starts, self.ends)
        many = self.lat.n_ids[self.occ_word]
        ends = np.cumsum(many)
        of_all = self.lat.ids[np.repeat(self.lat.ids_at[self.occ_word] - (ends - many), many) + np.arange(ends[-1])]
        cuts = np.concatenate([[0], ends])[self.occ_at]
        same = [n == m for n, m in zip(sp.normalize(self.texts), self.marked)]
        return [of_all[a:b] if ok else np.array(sp.encode(t), dtype=np.int32) for a, b, ok, t in zip(cuts[:-1], cuts[1:], same, self.texts)]

    def _walk(self, occ: np.ndarray, node: np.ndarray, turn: int) -> tuple[np.ndarray, np.ndarray]:
        """Draw from each node to its word's end: edges in order, and their number for each word."""
        lat, steps, count = self.lat, [], np.zeros(len(occ), dtype=np.int64)
        todo = np.flatnonzero(~lat.is_end[node])
        doc = self.occ_doc[occ]
        counter = self.keys[doc] + (occ - self.occ_at[doc]).astype(U64) * U64(0xA24BAED4963EE407) + U64(turn * 0x9FB21C651E98DF25 % (1 << 64))
        step = 0
        while len(todo):
            edge = lat.draw(node[todo], uniform(counter[todo] + U64(step * int(MIX) % (1 << 64))))
            steps.append((todo, edge))
            count[todo] += 1
            node[todo] = lat.end[edge]
            todo = todo[~lat.is_end[node[todo]]]
            step += 1
        first = np.concatenate([[0], np.cumsum(count)])
        flat = np.zeros(first[-1], dtype=np.int64)
        for k, (who, edge) in enumerate(steps):
            flat[first[who] + k] = edge
        return flat, count

    def _bounds(self, edges: np.ndarray, doc: np.ndarray, at: np.ndarray, before: np.ndarray, bound: np.ndarray, turn: int, gone: np.ndarray) -> np.ndarray:
        """The bound of what each place leaves: all edges but those that are gone there.

        ``at`` is the place in the document, ``before`` the log mass of what was chosen before it.
        """
        with np.errstate(divide="ignore"):
            rest = np.log(np.maximum(gone, 0.0))
        u = uniform(self.keys[doc] + at.astype(U64) * U64(0xC2B2AE3D27D4EB4F) + U64(turn * 0x165667B19E3779F9 % (1 << 64)) + U64(77))
        return truncated(before + rest, bound[doc], u)

    def top(self, k: int) -> tuple[list[list[tuple[np.ndarray, float, float]]], np.ndarray]:
        """For each document its samples (edges, log probability, bound) and the threshold."""
        out: list[list[tuple[np.ndarray, float, float]]] = [[] for _ in range(self.n)]
        empty = np.diff(self.doc_at) == 0
        for d in np.flatnonzero(empty):
            out[d].append((np.zeros(0, dtype=np.int64), 0.0, 0.0))
        kappa = np.full(self.n, -np.inf)
        if self.lat is None:
            return out, kappa
        lat = self.lat
        bound = -np.log(-np.log(uniform(self.keys + U64(13))))  # the root has log mass 0
        edges, count = self._walk(np.arange(len(self.occ_root)), self.occ_root.copy(), 0)
        occ = np.repeat(np.arange(len(self.occ_root)), count)
        doc = self.occ_doc[occ]
        place = np.searchsorted(doc, np.arange(self.n + 1))
        lq = np.concatenate([[0.0], np.cumsum(lat.log_q[edges])])
        before = lq[:-1] - lq[place[doc]]
        g = self._bounds(edges, doc, np.arange(len(edges)) - place[doc], before, bound, 0, lat.others[edges])
        # per document: its samples as (edges, words, before, bounds, excluded edges by place)
        live: list[list[dict]] = [[] for _ in range(self.n)]
        for d in np.flatnonzero(~empty):
            a, b = place[d], place[d + 1]
            live[d].append({"edges": edges[a:b], "occ": occ[a:b], "before": before[a:b], "g": g[a:b], "gone": {}, "bound": bound[d]})
            out[d].append((edges[a:b], float(lq[b] - lq[a]), float(bound[d])))
        todo = np.flatnonzero(~empty)
        for turn in range(1, k + 1):
            picks = []
            for d in todo:
                tops = [(s["g"][j := int(np.argmax(s["g"]))], i, j) for i, s in enumerate(live[d])]
                best = max(tops, key=lambda t: t[0])
                kappa[d] = best[0]
                if best[0] > -np.inf:
                    picks.append((d, *best))
            if turn == k or not picks:
                break
            todo = np.array([p[0] for p in picks])
            self._expand(picks, live, out, turn)
        return out, kappa

    def _expand(self, picks: list[tuple], live: list[list[dict]], out: list[list[tuple]], turn: int) -> None:
        """Complete the best node of each document to a segmentation."""
        lat = self.lat
        u = uniform(self.keys[[p[0] for p in picks]] + U64(turn * 0x27D4EB2F165667C5 % (1 << 64)) + U64(5))
        starts, nodes, heads = [], [], []
        for (d, g, i, j), x in zip(picks, u):
            s = live[d][i]
            own = int(s["edges"][j])
            node = int(lat.end[own] - lat.len[own])
            gone = [*s["gone"].get(j, []), own]
            cand = np.array([e for e in range(lat.first[node], lat.first[node + 1]) if e not in gone])
            cum = np.cumsum(lat.q[cand])
            alt = int(cand[min(int(np.searchsorted(cum, x * cum[-1], side="right")), len(cand) - 1)])
            left = float(cum[-1] - lat.q[alt]) if len(cand) > 1 else 0.0
            s["g"] = s["g"].copy()
            s["g"][j] = -np.inf
            heads.append((alt, gone, left))
            w = int(s["occ"][j])
            ws = np.arange(w, self.occ_at[d + 1])
            ns = self.occ_root[ws].copy()
            ns[0] = lat.end[alt]
            starts.append(ws)
            nodes.append(ns)
        occ = np.concatenate(starts)
        flat, count = self._walk(occ, np.concatenate(nodes), turn)
        words = np.repeat(occ, count)
        ends = np.cumsum([len(s) for s in starts])
        cum_tokens = np.concatenate([[0], np.cumsum(count)])
        a, made, bound = 0, [], np.empty(self.n)
        for (d, g, i, j), (alt, gone, left), e in zip(picks, heads, ends):
            s = live[d][i]
            tail = slice(cum_tokens[a], cum_tokens[e])
            edges = np.concatenate([s["edges"][:j], [alt], flat[tail]])
            own = np.concatenate([s["occ"][: j + 1], words[tail]])
            own[j] = s["occ"][j]
            lq = np.concatenate([[0.0], np.cumsum(lat.log_q[edges])])
            rest = lat.others[edges[j:]]
            rest[0] = left
            bound[d] = g
            made.append((edges[j:], np.full(len(edges) - j, d), np.arange(j, len(edges)), lq[j:-1], rest))
            live[d].append({"edges": edges, "occ": own, "before": lq[:-1], "gone": {j: gone}, "bound": g})
            out[d].append((edges, float(lq[-1]), float(g)))
            a = e
        tails, doc, at, before, rest = (np.concatenate(x) for x in zip(*made))
        new, a = self._bounds(tails, doc, at, before, bound, turn, rest), 0  # a document is picked once at most
        for (d, _, _, j), (tail, *_) in zip(picks, made):
            live[d][-1]["g"] = np.concatenate([np.full(j, -np.inf), new[a : a + len(tail)]])
            a += len(tail)

    def pieces(self, edges: np.ndarray) -> np.ndarray:
        """Piece ids, with characters outside the vocabulary as their bytes."""
        ids = self.lat.id[edges] if len(edges) else np.zeros(0, dtype=np.int32)
        if not len(ids) or ids.min() >= 0:
            return ids
        parts = [[i] if i >= 0 else self.vocab.byte_id[list(chr(-1 - i).encode("utf-8", "surrogatepass"))].tolist() for i in ids.tolist()]
        return np.array([x for p in parts for x in p], dtype=np.int32)


def decode_pieces(vocab: Vocabulary, ids: np.ndarray) -> bytes:
    """The text of piece ids, without the blank that encoding puts in front."""
    size = vocab.raw_len[ids]
    ends = np.cumsum(size)
    idx = np.repeat(vocab.raw_at[ids] - (ends - size), size) + np.arange(ends[-1] if len(ends) else 0)
    return vocab.raw_flat[idx].tobytes()[1:]


def log_inclusion(log_p: float, kappa: float) -> float:
    """Log of 1 - exp(-exp(log_p - kappa)): the chance that the score of this segmentation exceeds the threshold."""
    if kappa == -np.inf:
        return 0.0
    x = log_p - kappa
    return x - np.exp(x) / 2 if x < -20 else float(np.log(-np.expm1(-np.exp(x))))


SAMPLE = "array<struct<ids:array<int>,log_prob:double,log_inclusion:double>>"


def row_keys(keys: list, seed: int) -> np.ndarray:
    return np.array([xxhash.xxh64_intdigest(str(k).encode(), seed) for k in keys], dtype=U64)


def _slices(docs: DataFrame, id_col: str, text_col: str, model_path: str | None, alpha: float, seed: int, make, schema: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab = vocabulary(model_file(model_path), alpha)
        for batch in batches:
            for rows, texts in text_slices(batch, limit=SLICE):
                strs = [(t or b"").decode("utf-8", "replace") for t in texts]
                yield make(rows, strs, Slice(vocab, strs, row_keys(rows.column(0).to_pylist(), seed)), vocab)

    src = pick(docs, id_col, text_col).toDF("id", "text")
    return src.mapInArrow(run, f"id {src.schema['id'].dataType.simpleString()}, {schema}").withColumnRenamed("id", id_col)


def sample_segmentations(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = SAMPLES, alpha: float = 1.0, seed: int = 7, model_path: str | None = None) -> DataFrame:
    """id_col, samples: up to k distinct segmentations in falling perturbed score; one row per input row."""

    def make(rows, strs, part, vocab):
        found, kappa = part.top(k)
        flat = [(part.pieces(e), p, log_inclusion(p, kappa[d])) for d in range(len(strs)) for e, p, _ in found[d]]
        ends = np.cumsum([0, *[len(i) for i, _, _ in flat]]).astype(np.int32)
        ids = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([i for i, _, _ in flat] or [np.zeros(0, np.int32)]), pa.int32()))
        each = pa.StructArray.from_arrays([ids, pa.array([p for _, p, _ in flat], pa.float64()), pa.array([x for _, _, x in flat], pa.float64())], names=["ids", "log_prob", "log_inclusion"])
        of_doc = np.cumsum([0, *[len(f) for f in found]]).astype(np.int32)
        return pa.RecordBatch.from_arrays([rows.column(0), pa.ListArray.from_arrays(pa.array(of_doc), each)], names=["id", "samples"])

    return _slices(docs, id_col, text_col, model_path, alpha, seed, make, f"samples {SAMPLE}")


def sample_report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = SAMPLES, alpha: float = 1.0, seed: int = 7, model_path: str | None = None) -> DataFrame:
    """id_col, n_samples, and for each sample its number of pieces, hash, scores, and whether it decodes to the text.

    n_tokens, token_hash and tokens_decode are those of the library's own encoding of the whole text and of its decoding:
    every text goes to it whole, whatever words are known.
    """

    def make(rows, strs, part, vocab):
        found, kappa = part.top(k)
        sp = processor(model_file(model_path))
        plain = [sp.encode(t, return_type="numpy") for t in strs]  # one at a time, into arrays: a batch of lists takes the library longer
        back = [sp.decode(i) for i in plain]
        cols: dict[str, list] = {c: [] for c in ("n_samples", "n_pieces", "ids_hash", "log_prob", "log_inclusion", "decodes")}
        for d, text in enumerate(strs):
            ids = [part.pieces(e) for e, _, _ in found[d]]
            raw = text.replace(MARK, " ").encode("utf-8", "replace")
            cols["n_samples"].append(len(ids))
            cols["n_pieces"].append([len(i) for i in ids])
            cols["ids_hash"].append([xxhash.xxh64_hexdigest(i.astype("<i4").tobytes()) for i in ids])
            cols["log_prob"].append([p for _, p, _ in found[d]])
            cols["log_inclusion"].append([log_inclusion(p, kappa[d]) for _, p, _ in found[d]])
            cols["decodes"].append(all(decode_pieces(vocab, i) == raw for i in ids))
        cols["n_tokens"] = [len(i) for i in plain]
        cols["token_hash"] = [xxhash.xxh64_hexdigest(i.astype("<i4").tobytes()) for i in plain]
        cols["tokens_decode"] = [b == t.replace(MARK, " ") for b, t in zip(back, strs)]
        kinds = [pa.int32(), pa.list_(pa.int32()), pa.list_(pa.string()), pa.list_(pa.float64()), pa.list_(pa.float64()), pa.bool_(), pa.int64(), pa.string(), pa.bool_()]
        return pa.RecordBatch.from_arrays([rows.column(0), *[pa.array(v, t) for v, t in zip(cols.values(), kinds)]], names=["id", *cols])

    schema = "n_samples int, n_pieces array<int>, ids_hash array<string>, log_prob array<double>, log_inclusion array<double>, decodes boolean, n_tokens bigint, token_hash string, tokens_decode boolean"
    return _slices(docs, id_col, text_col, model_path, alpha, seed, make, schema)


def decode_ids(rows: DataFrame, ids_col: str, out_col: str = "text", model_path: str | None = None) -> DataFrame:
    """Adds the text of a column of piece ids; null ids decode to null."""

    @F.pandas_udf("string")
    def run(ids):
        sp = processor(model_file(model_path))
        return ids.map(lambda x: None if x is None else sp.decode([int(i) for i in x]))

    return rows.withColumn(out_col, run(F.col(f"`{ids_col}`")))
