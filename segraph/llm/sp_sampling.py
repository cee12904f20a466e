"""Sampled SentencePiece encodings without replacement, and decoding.

The lattice of a text is the product of its words' lattices, or with ``whole``
of those of its units, which are words, blank runs, newlines and tabs.  A tree search
over choices (next piece) perturbs total log-probabilities with Gumbel noise
from the root down: the root's value is a Gumbel variable; of a node's
children one inherits the node's value, the others get Gumbel variables
truncated at it.  Best-first expansion then meets the leaves, which are whole
segmentations, in the order of their perturbed values: a top-k sample without
replacement.  Following one value down to its leaf is an ancestral draw and is
done for all words at once; the siblings left behind go to the queue, which
need keep no more than the best k+1.  All rows of a slice are drawn together,
each with its own noise and queue.

All noise is a hash of the row key, the sample number and the place, so a row
gives the same samples wherever and however often it is computed.

Inclusion score of a sample: 1 - exp(-exp(log_prob - kappa)), kappa being the
(k+1)-th perturbed value; 1 if there is none.  Null and empty texts have one
sample, without pieces.  A text with fewer than k segmentations gives them all.
Ties have probability 0.  Repeated ids give equal samples for equal texts.
"""

from __future__ import annotations

import math
import zlib
from itertools import chain, repeat
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import pieces as P
from .shared import arrow_schema, prepare, tidy
from .textvec import mix, powers, slices

U = np.uint64
SAMPLES = 2
MOST_OPTIONS = 1_200_000  # of the lattices kept by a worker, 28 bytes each
MOST_CHARS = 40_000  # of new words at a time, unless one word is longer
SLICE = 256 << 10  # text bytes drawn together, unless one text is longer
GRAIN = 2.0**28  # log-probabilities are multiples of 1/GRAIN, so that sums are exact and rows don't depend on their neighbours
REACH = 38.0  # a Gumbel variable made from 53 random bits never exceeds its location by more
LEAD_BITS = 20  # leading bits by which a hash is found: far more values than pieces
FIRST = 24  # choices looked at before asking whether later ones can matter


class _Hashes:
    """Hashes of all pieces and their beginnings, for looking up substrings in bulk."""

    def __init__(self, v: P.Pieces):
        names = list(v.logp)
        size = np.array([len(n) for n in names], np.int64)
        start = np.repeat(np.cumsum(size) - size, size)
        cp = _code_points(names)
        k = np.arange(len(cp)) - start + 1
        h = self.of(_sums(cp), start, k)
        last = np.cumsum(size) - 1
        self.hash, at = np.unique(h, return_inverse=True)
        if len(np.unique(h[last])) < len(names) or len(self.hash) < len({n[:j] for n in names for j in range(1, len(n) + 1)}):
            raise ValueError("two pieces or beginnings share a hash")
        self.piece, self.longer = np.zeros((2, len(self.hash)), bool)
        self.piece[at[last]] = True
        self.longer[np.delete(at, last)] = True  # a longer piece begins like this
        self.logp = np.full(len(self.hash), -np.inf)
        self.logp[at[last]] = list(v.logp.values())
        self.id = np.zeros(len(self.hash), np.int32)
        self.id[at[last]] = [v.id[n] for n in names]
        # first of the sorted hashes from each value of the leading bits on
        self.lead = np.searchsorted(self.hash, np.arange(1 << LEAD_BITS, dtype=np.uint64) << U(64 - LEAD_BITS)).astype(np.int32)

    def find(self, h: np.ndarray) -> np.ndarray:
        """Places among the sorted hashes as by binary search, the last one for those beyond."""
        last = len(self.hash) - 1
        i = np.minimum(self.lead.take(h >> U(64 - LEAD_BITS)), last)
        far = np.flatnonzero(self.hash.take(i) < h)
        while len(far):
            i[far] += 1
            far = far[i[far] <= last]
            far = far[self.hash[i[far]] < h[far]]
        return np.minimum(i, last, out=i)

    @staticmethod
    def of(sums: np.ndarray, start: np.ndarray, k) -> np.ndarray:
        """Hashes of the k characters from start on, by _sums of all."""
        return mix((sums[start + k] - sums[start]) * powers("inv", len(sums))[start] + np.asarray(k).astype(np.uint64))


def _code_points(words: list[str]) -> np.ndarray:
    return np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)


def _sums(cp: np.ndarray) -> np.ndarray:
    c = np.zeros(len(cp) + 1, np.uint64)
    np.cumsum(mix(cp.astype(np.uint64) + U(0x51)) * powers("base", len(cp)), out=c[1:])
    return c


class Lattices:
    """Choice nodes of words: node = position in a word; options = pieces from
    there, with probabilities given that the word is completed.

    Per option: log-probability, next node (-1 at the word's end), node number
    plus cumulative probability, and piece id (-1 - code point for a character
    that falls back to its bytes)."""

    def __init__(self, vocab: P.Pieces):
        self.vocab, self.hashes = vocab, _Hashes(vocab)
        self.clear()

    def clear(self):
        self.root: dict[str, int] = {}
        self.nodes = self.options = 0
        self.used = np.zeros(0, np.int32)  # by a word's first node: how many slices had the word
        self._room = [np.zeros(1, np.int32), np.zeros(0), np.zeros(0, np.int32), np.zeros(0), np.zeros(0, np.int32)]

    @property
    def size(self) -> int:
        return self.options

    @property
    def arrays(self):
        """first option of a node (one more than nodes); log-probability, next node, cumulative, piece of options."""
        return (self._room[0][: self.nodes + 1], *(r[: self.options] for r in self._room[1:]))

    def _append(self, first, *columns) -> None:
        """Into buffers that double, so that growing costs no copy of all each time."""
        ends = (self.nodes + len(first), *[self.options + len(columns[0])] * 4)
        for i, (end, new) in enumerate(zip(ends, (first, *columns))):
            if end > len(self._room[i]):
                grown = np.zeros(max(end, 2 * len(self._room[i])), self._room[i].dtype)
                grown[: len(self._room[i])] = self._room[i]
                self._room[i] = grown
            self._room[i][end - len(new) : end] = new
        self.nodes, self.options = self.nodes + len(first) - 1, ends[1]

    def touch(self, roots: np.ndarray) -> None:
        """Counts a slice with the words of these first nodes."""
        self.used = np.concatenate([self.used, np.zeros(self.nodes - len(self.used), np.int32)])
        seen = np.zeros(self.nodes, bool)
        seen[roots] = True
        self.used += seen

    def shrink(self, most: int) -> None:
        """Keeps the words that came more than once, the most used first, up to ``most`` options; their counts are halved."""
        self.touch(np.zeros(0, np.int64))
        words = list(self.root)
        root = np.fromiter(self.root.values(), np.int64, len(words))
        size = np.fromiter(map(len, words), np.int64, len(words))
        first = self.arrays[0]
        many, used = (first[root + size] - first[root]).astype(np.int64), self.used[root]
        order = np.argsort(-used, kind="stable")
        kept = np.sort(order[(np.cumsum(many[order]) <= most) & (used[order] > 1)])
        root, size, many, used = root[kept], size[kept], many[kept], used[kept]
        nodes, options = _runs(root, size), _runs(first[root].astype(np.int64), many)
        new = np.cumsum(size) - size
        moved = np.repeat((new - root).astype(np.int32), many)
        self._room[0] = np.concatenate([[0], np.cumsum(first[nodes + 1] - first[nodes])]).astype(np.int32)
        del first
        for i in range(1, 5):  # one after the other, so that no two copies of all are held
            self._room[i] = self._room[i][options]
        self._room[2] += np.where(self._room[2] < 0, 0, moved)
        self._room[3] += moved
        self.nodes, self.options = len(nodes), len(options)
        self.used = np.zeros(self.nodes, np.int32)
        self.used[new] = used >> 1
        self.root = dict(zip([words[i] for i in kept.tolist()], new.tolist()))

    def add(self, words) -> None:
        part, chars = [], 0
        for w in set(words).difference(self.root):
            part.append(w)
            chars += len(w)
            if chars >= MOST_CHARS:
                self._add(part)
                part, chars = [], 0
        if part:
            self._add(part)

    def roots(self, words: list[str]) -> np.ndarray:
        """First nodes of the words of a slice, new ones being added."""
        out = np.fromiter(map(self.root.get, words, repeat(-1)), np.int64, len(words))
        new = np.flatnonzero(out < 0)
        if len(new):
            rest = [words[i] for i in new.tolist()]
            self.add(rest)
            out[new] = [self.root[w] for w in rest]
        self.touch(out)
        return out

    def _add(self, words: list[str]) -> None:
        v, hs = self.vocab, self.hashes
        cp = _code_points(words)
        n = len(cp)
        size = np.array([len(w) for w in words], np.int64)
        end = np.repeat(np.cumsum(size), size)
        left = end - np.arange(n)  # characters from here to the word's end
        sums = _sums(cp)
        frm, to, lp, pid = [], [], [], []
        p, k = np.arange(n), 0
        while len(p):  # places from where k characters more may begin a piece
            k += 1
            h = hs.of(sums, p, k)
            i = hs.find(h)
            begun = hs.hash[i] == h
            ok = begun & hs.piece[i]
            frm.append(p[ok])
            to.append(p[ok] + k)
            lp.append(hs.logp[i[ok]])
            pid.append(hs.id[i[ok]])
            if k == 1:
                bare = np.flatnonzero(~ok)
                frm.append(bare)
                to.append(bare + 1)
                code, at = np.unique(cp[bare], return_inverse=True)
                lp.append(v.floor * np.array([len(chr(c).encode("utf-8", "surrogatepass")) for c in code.tolist()], np.int64)[at])
                pid.append((-1 - cp[bare].astype(np.int64)).astype(np.int32))
            p = p[begun & hs.longer[i] & (left[p] > k)]
        frm, to, lp, pid = (np.concatenate(x) for x in (frm, to, lp, pid))
        order = np.argsort(left[frm] * (n + 1) + frm)  # nodes by distance from the word's end
        frm, to, lp, pid = frm[order], to[order], lp[order], pid[order]
        beta = np.zeros(n + 1)
        score = np.empty(len(frm))
        cuts = np.searchsorted(left[frm], np.arange(1, int(left.max(initial=0)) + 2))
        for a, b in zip(cuts[:-1], cuts[1:]):
            if a == b:
                continue
            x = lp[a:b] + np.where(to[a:b] == end[frm[a:b]], 0.0, beta[to[a:b]])
            f = frm[a:b]
            st = np.flatnonzero(np.concatenate([[True], f[1:] != f[:-1]]))
            top = np.maximum.reduceat(x, st)
            rep = np.diff(np.append(st, b - a))
            total = top + np.log(np.add.reduceat(np.exp(x - np.repeat(top, rep)), st))
            beta[f[st]] = total
            score[a:b] = x - np.repeat(total, rep)
        order = np.argsort(frm + np.minimum(-score / 1024, 0.999))  # likely options first, so that a draw finds its own soon
        frm, to, score, pid = frm[order], to[order], score[order], pid[order]
        base, held = self.nodes, self.options
        st = np.searchsorted(frm, np.arange(n + 1))
        q = np.exp(score)
        run = np.cumsum(q)
        run -= np.repeat((run - q)[st[:-1]], np.diff(st))
        edge = np.minimum(run, 1.0)
        edge[st[1:] - 1] = 1.0
        score = np.round(score * GRAIN) / GRAIN
        self._append(held + st, score, np.where(to == end[frm], -1, base + to), base + frm + edge, pid)
        self.root.update(zip(words, (base + np.cumsum(size) - size).tolist()))


def _seeds(keys: np.ndarray, tag: int) -> np.ndarray:
    return mix(keys ^ U(tag * 0x9E3779B97F4A7C15 % 2**64))


def _uniform(seed: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Uniform numbers in (0, 1) for places of rows, by hash."""
    h = mix(place.astype(np.uint64) * U(0x2545F4914F6CDD1D) + seed)
    return (h >> U(11)).astype(np.float64) * 2.0**-53 + 2.0**-54


def _below(mu: np.ndarray, top: np.ndarray, u: np.ndarray) -> np.ndarray:
    """Gumbel variables of location mu, given that they are below top."""
    with np.errstate(over="ignore"):
        return mu - np.log(np.exp(np.minimum(mu - top, 700)) - np.log(u))


def _runs(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start[0], start[0]+1, ... size[0] of them, then those of start[1], and so on."""
    return np.arange(size.sum()) + np.repeat(start - (np.cumsum(size) - size), size)


class Drawn(NamedTuple):
    """One sampled segmentation: its options in text order, log-probability,
    perturbed value, sample number and inclusion score."""

    option: np.ndarray
    total: float
    value: float
    number: int
    inclusion: float


class _Rows:
    """Rows of words that are sampled together."""

    def __init__(self, lat: Lattices, rows: list[list[str]], keys: np.ndarray):
        self.lat, self.keys, self.n = lat, keys, len(rows)
        self.size = np.array([len(r) for r in rows], np.int64)
        self.word0 = np.cumsum(self.size) - self.size
        self.roots = lat.roots(list(chain.from_iterable(rows)))
        self.row = np.repeat(np.arange(self.n), self.size)
        self.local = np.arange(len(self.roots)) - self.word0[self.row]
        # all drawn paths one behind the other
        self.word, self.step, self.node, self.option = (np.zeros(0, np.int64) for _ in range(4))
        self.before = np.zeros(0)

    def walk(self, word, node, step, seed):
        """Draws the words to their ends; word, step, node, option in text order."""
        first, _, nxt, cum, _ = self.lat.arrays
        words, steps, nodes, opts = [word[:0]], [step[:0]], [step[:0]], [step[:0]]
        start = np.zeros(len(self.roots), np.int64)
        start[word] = step
        while len(word):
            goal = node + _uniform(seed[self.row[word]], (self.local[word] << 24) + step)
            o = first[node].astype(np.int64)
            far = np.flatnonzero(cum[o] < goal)
            while len(far):
                o[far] += 1
                far = far[cum[o[far]] < goal[far]]
            words.append(word)
            steps.append(step)
            nodes.append(node)
            opts.append(o)
            to = nxt[o]
            go = to >= 0
            word, node, step = word[go], to[go], step[go] + 1
        got = [np.concatenate(c) for c in (words, steps, nodes, opts)]
        w, s = got[:2]
        each = np.bincount(w, minlength=len(self.roots))
        place = (np.cumsum(each) - each - start)[w] + s
        out = [np.empty_like(c) for c in got]
        for a, c in zip(out, got):
            a[place] = c
        return out

    def draw(self, number: int, rows: np.ndarray, at: np.ndarray | None = None, first_of: np.ndarray | None = None, option: np.ndarray | None = None):
        """Paths of the given rows: drawn anew, or the choices from first_of up
        to ``at``, then ``option`` there, and the rest drawn.  Appends them and
        gives their starts, ends and total log-probabilities."""
        _, logq, nxt, _, _ = self.lat.arrays
        seed = _seeds(self.keys, 2 * number + 1)
        if at is None:
            head, w0 = np.zeros(len(rows), np.int64), self.word0[rows]
        else:
            head, w0 = at - first_of + 1, self.word[at] + 1
        word = _runs(w0, self.word0[rows] + self.size[rows] - w0)
        node, step = self.roots[word], np.zeros(len(word), np.int64)
        if at is not None:
            on = nxt[option] >= 0
            word = np.concatenate([self.word[at][on], word])
            node = np.concatenate([nxt[option[on]], node])
            step = np.concatenate([self.step[at][on] + 1, step])
        tail = self.walk(word, node, step, seed)
        size = np.zeros(self.n, np.int64)
        if len(tail[0]):
            size += np.bincount(self.row[tail[0]], minlength=self.n)
        size = size[rows]
        start = np.cumsum(head + size) - (head + size)
        new = [np.empty(int((head + size).sum()), np.int64) for _ in range(4)]
        kept, put = (_runs(first_of, head), _runs(start, head)) if at is not None else (head[:0], head[:0])
        rest = _runs(start + head, size)
        for a, old, t in zip(new, (self.word, self.step, self.node, self.option), tail):
            a[put] = old[kept]
            a[rest] = t
        if at is not None:
            new[3][start + head - 1] = option
        q = np.concatenate([[0.0], np.cumsum(logq[new[3]])])
        end = start + head + size
        before = q[:-1] - np.repeat(q[start], head + size)
        base = len(self.word)
        self.word, self.step, self.node, self.option = (np.concatenate(x) for x in zip((self.word, self.step, self.node, self.option), new))
        self.before = np.concatenate([self.before, before])
        return base + start, base + end, q[end] - q[start]


def sample_rows(lat: Lattices, rows: list[list[str]], k: int, keys: np.ndarray):
    """k distinct segmentations at most of each row, in the order of falling
    perturbed values, as columns: row, number, total log-probability, perturbed
    value, inclusion score, n+1 offsets, options.  Words new to the lattices are added."""
    x = _Rows(lat, rows, keys)
    first, logq, _, _, _ = lat.arrays
    n = x.n
    value = -np.log(-np.log(_uniform(_seeds(keys, 0), np.zeros(n, np.int64))))
    # the best k siblings of each row that no sample has used: value, place among all paths, option, start of their path
    qv = np.full((n, k + 1), -np.inf)
    qa, qo, qs = (np.zeros((n, k + 1), np.int64) for _ in range(3))
    live = np.arange(n)
    start, end, total = x.draw(0, live)
    since = start.copy()
    out = []
    for j in range(k):
        out.append((live, np.full(len(live), j), total, value[live], start, end))
        at, want = since.copy(), k - j
        seed = _seeds(keys, 2 * j + 4)
        todo, step = np.arange(len(live)), FIRST
        while len(todo):
            stop, step = np.minimum(at[todo] + step, end[todo]), 4 * step
            pos = _runs(at[todo], stop - at[todo])
            of = np.repeat(todo, stop - at[todo])
            node = x.node[pos]
            many = first[node + 1] - first[node]
            rep = np.repeat(np.arange(len(pos)), many)
            o = _runs(first[node].astype(np.int64), many)
            mu = x.before[pos][rep] + logq[o]
            off = (o != x.option[pos][rep]) & (mu + REACH >= qv[live[of], want - 1][rep])
            rep, o, mu = rep[off], o[off], mu[off]
            p, r = pos[rep], live[of[rep]]
            g = _below(mu, value[r], _uniform(seed[r], (((x.local[x.word[p]] << 24) + x.step[p]) << 6) + o - first[node[rep]]))
            # the best of old and new ones, by row
            rows_, = np.nonzero(np.bincount(live[todo], minlength=n))
            old_r, old_c = np.nonzero(qv[rows_] > -np.inf)
            old_r = rows_[old_r]
            rr = np.concatenate([old_r, r])
            gg = np.concatenate([qv[old_r, old_c], g])
            aa = np.concatenate([qa[old_r, old_c], p])
            oo = np.concatenate([qo[old_r, old_c], o])
            ss = np.concatenate([qs[old_r, old_c], start[of[rep]]])
            order = np.lexsort((-gg, rr))
            rr = rr[order]
            rank = np.arange(len(rr)) - np.searchsorted(rr, rr)
            best = rank < want
            order, rr, rank = order[best], rr[best], rank[best]
            qv[rows_] = -np.inf
            qv[rr, rank], qa[rr, rank], qo[rr, rank], qs[rr, rank] = gg[order], aa[order], oo[order], ss[order]
            at[todo] = stop
            more = stop < end[todo]
            # log-probabilities only fall along the text, so far choices can't reach the best ones kept
            todo, stop = todo[more], stop[more]
            todo = todo[x.before[stop] + REACH >= qv[live[todo], want - 1]]
        if j == k - 1:
            break
        live_next = live[qv[live, 0] > -np.inf]
        if not len(live_next):
            break
        live = live_next
        value[live] = qv[live, 0]
        at, option, head = qa[live, 0], qo[live, 0], qs[live, 0]
        for q, none in ((qv, -np.inf), (qa, 0), (qo, 0), (qs, 0)):
            q[live, :-1] = q[live, 1:]
            q[live, -1] = none
        start, end, total = x.draw(j + 1, live, at, head, option)
        since = start + (at - head) + 1
    row, number, total, val, start, end = (np.concatenate(c) for c in zip(*out))
    kappa = qv[:, 0][row]
    with np.errstate(over="ignore"):
        inclusion = np.where(kappa == -np.inf, 1.0, -np.expm1(-np.exp(np.minimum(total - np.where(kappa == -np.inf, 0, kappa), 700.0))))
    order = np.lexsort((number, row))
    start, size = start[order], (end - start)[order]
    return row[order], number[order], total[order], val[order], inclusion[order], np.concatenate([[0], np.cumsum(size)]), x.option[_runs(start, size)]


def sample(lat: Lattices, words: list[str], k: int, key: int) -> list[tuple[Drawn, float, float]]:
    """(segmentation, log-probability, inclusion score) of one row's samples."""
    row, number, total, value, inc, of, option = sample_rows(lat, [words], k, np.array([key], np.uint64))
    return [(Drawn(option[a:b], float(t), float(v), int(j), float(i)), float(t), float(i)) for j, t, v, i, a, b in zip(number, total, value, inc, of[:-1], of[1:])]


def _ids(lat: Lattices, option: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids of option sequences, characters without a piece as their bytes, with new offsets."""
    ids = lat.arrays[4][option]
    bare = np.flatnonzero(ids < 0)
    if not len(bare):
        return ids, of
    chars, which = np.unique(ids[bare], return_inverse=True)
    by = [np.array([lat.vocab.bytes[b] for b in chr(-1 - c).encode("utf-8", "surrogatepass")], np.int32) for c in chars.tolist()]
    size = np.ones(len(ids), np.int64)
    width = np.array([len(b) for b in by], np.int64)
    size[bare] = width[which]
    end = np.concatenate([[0], np.cumsum(size)])
    out = np.repeat(ids, size)
    flat, lead = np.concatenate(by), np.cumsum(width) - width
    out[_runs(end[bare], size[bare])] = flat[_runs(lead[which], size[bare])]
    return out, end[of]


def piece_ids(lat: Lattices, path: Drawn) -> np.ndarray:
    """Ids of one segmentation."""
    return _ids(lat, path.option, np.array([0, len(path.option)]))[0]


class _Decoder:
    """Bytes of many id sequences at once; marks are blanks, and the first one of a sequence is dropped."""

    def __init__(self, vocab: P.Pieces):
        text = [bytes([vocab.byte_of[i]]) if i in vocab.byte_of else t.replace(P.MARK, " ").encode("utf-8", "surrogatepass") for i, t in enumerate(vocab.text)]
        self.size = np.array([len(t) for t in text], np.int64)
        self.lead = np.cumsum(self.size) - self.size
        self.data = np.frombuffer(b"".join(text), np.uint8)

    def __call__(self, ids: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        size = self.size[ids]
        end = np.concatenate([[0], np.cumsum(size)])[of]
        data = self.data[_runs(self.lead[ids], size)]
        lead = np.flatnonzero(np.diff(end))
        lead = lead[data[end[lead]] == 32]
        keep = np.ones(len(data), bool)
        keep[end[lead]] = False
        dropped = np.zeros(len(of), np.int64)
        dropped[lead + 1] = 1
        return data[keep], end - np.cumsum(dropped)


_local: dict[str, tuple[Lattices, _Decoder]] = {}


def encode(docs: DataFrame, vocab_path: str, k: int = SAMPLES, seed: int = 0, keep_ids: bool = True, whole: bool = False) -> DataFrame:
    """k rows per document at most: doc_id, sample, n_pieces, log_prob,
    perturbed, inclusion, round_trip (decoding gives back the words, or the text
    itself if whole), the crc32 of the ids and, unless keep_ids is off, the ids.

    Null ids count as the empty id text; extra columns don't reach the result."""
    prepare(docs.sparkSession)
    ddl = "doc_id bigint, sample int, n_pieces bigint, log_prob double, perturbed double, inclusion double, round_trip boolean, ids_crc32 bigint" + (", ids array<int>" if keep_ids else "")
    schema = arrow_schema(ddl)

    def work(it):
        if vocab_path not in _local:
            vocab = P.load(vocab_path)
            _local[vocab_path] = Lattices(vocab), _Decoder(vocab)
        lat, decode = _local[vocab_path]
        for batch in it:
            for part in slices(batch, "text", SLICE):
                given = [t or "" for t in part.column(1).to_pylist()]
                split = [P.units_of(t) if whole else P.words_of(t) for t in given]
                if lat.size > MOST_OPTIONS:
                    lat.shrink(MOST_OPTIONS // 2)
                doc = part.column(0).to_pylist()
                keys = np.array([zlib.crc32(("" if d is None else str(d)).encode()) << 32 | (seed & 0xFFFFFFFF) for d in doc], np.uint64)
                row, number, total, value, inc, of, option = sample_rows(lat, split, k, keys)
                ids, of = _ids(lat, option, of)
                data, ends = decode(ids, of)
                raw = data.tobytes()
                plain = [(t if whole else " ".join(w[1:] for w in ws)).encode() for t, ws in zip(given, split)]
                back = [raw[a:b] == plain[r] for r, a, b in zip(row.tolist(), ends[:-1].tolist(), ends[1:].tolist())]
                raw = ids.astype("<u4").tobytes()
                crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(of[:-1].tolist(), of[1:].tolist())]
                columns = [part.column(0).take(pa.array(row)), pa.array(number.astype(np.int32)), pa.array(np.diff(of)), pa.array(total), pa.array(value), pa.array(inc), pa.array(back), pa.array(crc, pa.int64())]
                if keep_ids:
                    columns.append(pa.ListArray.from_arrays(pa.array(of.astype(np.int32)), pa.array(ids.astype(np.int32))))
                yield pa.RecordBatch.from_arrays(columns, schema=schema)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(work), ddl)
