"""SentencePiece encoding and decoding, with sampling of distinct segmentations.

A text is a lattice whose paths are its segmentations into vocabulary pieces. Pieces have Zipf weights by their rank in the
model, raised to `sharpness`; a path's probability is the product of its weights over the sum of all paths. No piece of the
vocabulary goes on over the start of a word, so the lattice is a chain of words and a path's probability a product over words.

Sampling without replacement is a perturbed A-star search. Each set of paths has a Gumbel-perturbed log-mass, which is the
perturbed score of its best path; the search takes the set with the highest one, draws that best path, and splits what is left
by the first word at which a path departs from it. The parts' perturbed scores are Gumbel variables cut off at the parent's.
The k paths found are exactly the k highest perturbed paths. The score of the next one turns into inclusion
probabilities. The random numbers of a row depend on its key alone.

Texts are worked on some hundred at a time: the lattices of all words that a batch needs are solved side by side in arrays,
and so are the draws of words that leave their best path. Words that are long or have letters outside the arrays go one by one.
What a worker keeps between batches is one table of at most `entries` words and those of a batch.

Defined results: null and empty texts have one segmentation, without pieces. Where a text has fewer segmentations than asked
for, all are given with inclusion 1. Characters outside the vocabulary become byte pieces. Rows that repeat a key and text get
the same samples. An empty table gives an empty result.
"""

from __future__ import annotations

import functools
import math
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from .common import HELD, bounded_batches, tidy, without_cycles

MARK = "▁"
SAMPLES, SHARPNESS = 2, 1.0
#: Rank of byte pieces, and the addend of Zipf's law.
BYTE_RANK, ZIPF = 1e6, 2.7
#: Longer words are added up in logarithms.
PLAIN_LENGTH = 40
#: Letters that the arrays know, words solved side by side, and rows and characters of a batch.
LETTERS, SIDE_BY_SIDE, BATCH_ROWS, BATCH_CHARS = 511, 4096, 256, 1 << 20
U = np.uint64


def uniforms(seeds: np.ndarray, step: int) -> np.ndarray:
    """Numbers in [0, 1) that depend on (seed, step) alone."""
    z = seeds + U((step + 1) * 0x9E3779B97F4A7C15 % (1 << 64))
    z = (z ^ (z >> U(30))) * U(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> U(27))) * U(0x94D049BB133111EB)
    return ((z ^ (z >> U(31))) >> U(11)).astype(float) / float(1 << 53)


class PieceTree:
    """Pieces as a tree of letters: state 0 is dead, 1 the root.

    The letters of `bare` are written as one or two byte pieces; until then they have ids from `size` on.
    """

    def __init__(self, weights: dict[str, float], ids: dict[str, int], bare: dict[str, list[int]], size: int):
        self.size, self.spelled = size, np.array([(x[0], x[-1], len(x)) for x in bare.values()], np.int32).reshape(-1, 3)
        ids = ids | {ch: size + k for k, ch in enumerate(bare)}
        alone = [(ch, n) for ch, n in Counter("".join(weights)).items() if ch in weights]
        known = sorted(alone, key=lambda x: (x[0] > "\u017f", -x[1], x[0]))[:LETTERS]
        self.letter = np.zeros(0x110000, np.uint16)
        self.letter[[ord(ch) for ch, _ in known]] = np.arange(1, len(known) + 1)
        self.known = frozenset(ch for ch, _ in known)
        root: dict = {}
        for p in weights:
            if self.known.issuperset(p):
                node = root
                for ch in p:
                    node = node.setdefault(ch, {})
                node[0] = p
        nodes, parents, steps = [root], [0], [0]
        for at, node in enumerate(nodes):  # grows while it is walked
            for ch, child in node.items():
                if ch != 0:
                    nodes.append(child)
                    parents.append(at)
                    steps.append(int(self.letter[ord(ch)]))
        self.weight, self.piece = np.zeros(len(nodes) + 1), np.full(len(nodes) + 1, -1, np.int32)
        children: list[list] = [[] for _ in range(len(nodes) + 1)]
        for k, node in enumerate(nodes, 1):
            if 0 in node:
                self.weight[k], self.piece[k] = weights[node[0]], ids[node[0]]
            if k > 1:
                children[parents[k - 1] + 1].append((steps[k - 1], k))
        # The children of a state stand at its base plus their letters, in slots that no other state uses.
        self.base = np.zeros(len(nodes) + 1, np.int32)
        used, low = bytearray(3 * len(nodes) + 64 * LETTERS), LETTERS
        slots: dict[int, tuple[int, int]] = {}
        single = False
        for k in sorted((k for k, x in enumerate(children) if x), key=lambda k: -len(children[k])):
            letters = [ch for ch, _ in children[k]]
            if len(letters) == 1 and not single:
                single, low = True, LETTERS  # the gaps that the larger families left
            base = max(0, low - letters[0])
            while any([used[base + ch] for ch in letters]):
                base += 1
            self.base[k], low = base, base + letters[0]
            for ch, child in children[k]:
                used[base + ch] = 1
                slots[base + ch] = k, child
        self.owner, self.next = np.zeros(len(used) + LETTERS + 1, np.int32), np.zeros(len(used) + LETTERS + 1, np.int32)
        self.owner[list(slots)], self.next[list(slots)] = np.array(list(slots.values()), np.int32).T

    def down(self, state: np.ndarray, code: np.ndarray) -> np.ndarray:
        at = self.base[state] + code
        return np.where(self.owner[at] == state, self.next[at], 0)

    def written(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids with bare letters as bytes, how many of them each given id has become)."""
        bare = np.flatnonzero(ids >= self.size)
        count = np.ones(len(ids), np.int64)
        if not len(bare):
            return ids, count
        count[bare] = self.spelled[ids[bare] - self.size, 2]
        out, start = np.repeat(ids, count), (np.cumsum(count) - count)[bare]
        first, last = self.spelled[ids[bare] - self.size, :2].T
        out[start], out[start + count[bare] - 1] = first, last
        return out, count


class WordLattices:
    """Lattices of many words side by side, one column a word, ends aligned: sums over paths, best ways, draws."""

    def __init__(self, tree: PieceTree, words: list[str]):
        self.tree = tree
        size = np.array([len(w) for w in words])
        n, width = len(words), int(size.max())
        order = np.argsort(-size, kind="stable")
        self.column = np.empty(n, np.int64)  # of each word
        self.column[order] = np.arange(n)
        self.width, self.first = width, width - size[order]
        letters = tree.letter[np.frombuffer("".join(words).encode("utf-32-le"), np.uint32)]
        self.code = code = np.zeros((width, n), np.uint16)
        code[np.arange(len(letters)) - np.repeat(np.cumsum(size) - width, size), np.repeat(self.column, size)] = letters
        self.total, best = np.zeros((width + 1, n)), np.zeros((width + 1, n))
        self.total[width] = best[width] = 1.0
        # Per place: mass of the ways beside the best one and of the best one; its end and piece.
        self.other, self.term = np.zeros((width, n)), np.zeros((width, n))
        self.way, self.piece = np.full((width, n), width, np.int16), np.full((width, n), -1, np.int32)
        for i in range(width - 1, -1, -1):
            some = np.arange(np.searchsorted(self.first, i, "right"))
            o, t, b, w, p = (x[i] for x in (self.other, self.term, best, self.way, self.piece))
            state = tree.down(np.ones(len(some), np.int32), code[i, some])
            for j in range(i + 1, width + 1):
                weight = tree.weight[state]
                mass, value = weight * self.total[j, some], weight * best[j, some]
                up = value > b[some]
                o[some] += np.where(up, t[some], mass)
                rise = some[up]
                t[rise], b[rise], w[rise], p[rise] = mass[up], value[up], j, tree.piece[state[up]]
                if j == width:
                    break
                state = tree.down(state, code[j, some])
                go = state > 0
                if not go.any():
                    break
                some, state = some[go], state[go]
            self.total[i] = o + t
        whole = np.arange(n)
        with np.errstate(divide="ignore", invalid="ignore"):
            self.sound = (best[self.first, whole] > 1e-280) & np.isfinite(self.total[self.first, whole])
            self.p = best[self.first, whole] / self.total[self.first, whole]
            # Chance of leaving the best path at each of its steps.
            pos, stay, leave = self.first.copy(), np.ones(n), []
            while (on := np.flatnonzero(pos < width)).size:
                at = pos[on]
                gone = np.zeros(n)
                gone[on] = stay[on] * self.other[at, on] / self.total[at, on]
                stay[on] *= self.term[at, on] / self.total[at, on]
                pos[on] = self.way[at, on]
                leave.append(gone)
        self.leave = np.array(leave)
        self.until = np.cumsum(self.leave, axis=0)
        self.q = self.until[-1]

    def paths(self, column: np.ndarray, seeds: np.ndarray | None = None) -> tuple[list[bytes], np.ndarray]:
        """(ids, log-probability) of the best path of each column or, with `seeds`, of one drawn from all others.

        Such a draw follows the best path up to a drawn step, leaves it there, and goes on freely.
        """
        tree, width = self.tree, self.width
        pos, logs, steps = self.first[column], np.zeros(len(column)), []
        turn = np.full(len(column), width + 1)
        if seeds is not None:
            turn = (self.until[:, column] <= uniforms(seeds, 0) * self.q[column]).sum(0)
            last = len(self.leave) - 1 - np.argmax(self.leave[::-1] > 0, axis=0)
            turn = np.minimum(turn, last[column])
        step = 0
        while (on := np.flatnonzero(pos < width)).size:
            at, col = pos[on], column[on]
            end, piece, mass = self.way[at, col].astype(np.int64), self.piece[at, col], self.term[at, col]
            free = np.flatnonzero(turn[on] <= step)
            if len(free):
                a, c, off = at[free], col[free], turn[on][free] == step
                avoid = np.where(off, end[free], -1)
                goal = uniforms(seeds[on[free]], step + 1) * np.where(off, self.other[a, c], self.total[a, c])
                run, k, state, j = np.zeros(len(free)), np.arange(len(free)), tree.down(np.ones(len(free), np.int32), self.code[a, c]), a + 1
                while len(k):
                    v = np.where(j == avoid[k], 0.0, tree.weight[state] * self.total[j, c[k]])
                    take = v > 0  # the last way with a weight stands where rounding leaves the goal out of reach
                    to = free[k[take]]
                    end[to], piece[to], mass[to] = j[take], tree.piece[state[take]], v[take]
                    run[k] += v
                    go = (run[k] <= goal[k]) & (j < width)
                    k, j, state = k[go], j[go], state[go]
                    state = tree.down(state, self.code[j, c[k]])
                    go = state > 0
                    k, j, state = k[go], j[go] + 1, state[go]
            with np.errstate(divide="ignore", invalid="ignore"):
                logs[on] += np.log(mass / self.total[at, col])
            taken = np.full(len(column), -1, np.int32)
            taken[on] = piece
            steps.append(taken)
            pos[on] = end
            step += 1
        steps = np.array(steps).T
        there = steps >= 0
        ids, count = tree.written(steps[there])
        ends = np.r_[0, np.cumsum(count)][np.cumsum(there.sum(1))] * 4
        flat = ids.astype("<i4").tobytes()
        return [flat[a:b] for a, b in zip([0, *ends[:-1].tolist()], ends.tolist())], logs


class _Places(dict):
    """Place of each word in the table; words that are asked for and not in it get the next places and wait in `fresh`."""

    def __init__(self):
        super().__init__()
        self.fresh: list[str] = []

    def __missing__(self, word: str) -> int:
        at = self[word] = len(self)
        self.fresh.append(word)
        return at


class _Search:
    """The search of one text: its words' places in the table, its random numbers, paths found and open sets."""

    def __init__(self, at: np.ndarray, rng):
        self.at, self.rng = at, rng
        self.found: list = []  # (path, log-probability, perturbed score)
        self.open: list = []  # (perturbed score per word of departure, path, first such word, paths excluded there)
        self.value = math.inf


class PieceLattice:
    """Pieces, weights and the words met so far of one model."""

    def __init__(self, model: str, sharpness: float = SHARPNESS, entries: int = 300_000):
        import sentencepiece

        self.processor = sp = sentencepiece.SentencePieceProcessor(model_file=model)
        n = sp.get_piece_size()
        self.pieces = [sp.id_to_piece(i) for i in range(n)]
        self.bytes = {int(self.pieces[i][1:-1], 16): i for i in range(n) if sp.is_byte(i)}
        self.byte_of = {i: b for b, i in self.bytes.items()}
        self.written = [bytes([self.byte_of[i]]) if i in self.byte_of else p.encode() for i, p in enumerate(self.pieces)]
        self.flat, self.long = np.frombuffer(b"".join(self.written), np.uint8), np.fromiter(map(len, self.written), np.int32, n)
        self.start = np.cumsum(self.long, dtype=np.int32) - self.long
        log_weight = lambda rank: -sharpness * math.log(rank + ZIPF)
        self.ids, self.log_w = {}, {}
        for i, p in enumerate(self.pieces):
            if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)):
                self.ids[p] = i
                self.log_w[p] = log_weight(max(0.0, -sp.get_score(i)))
        if any(MARK in p.lstrip(MARK) for p in self.ids):
            raise ValueError("pieces go on over word starts; this lattice does not")
        self.log_byte = log_weight(BYTE_RANK)
        self.longest = max(map(len, self.ids))
        # Weights are scaled by character, so that products of usual words stay near 1.
        scale = sharpness * 2.2
        weights = {p: math.exp(x + scale * len(p)) for p, x in self.log_w.items()}
        # Latin letters and signs outside the vocabulary, such as a line feed, are their bytes.
        bare = {ch: self.byte_ids(ch) for ch in map(chr, range(0x180)) if ch not in self.ids}
        weights |= {ch: math.exp(self.log_byte * len(x) + scale) for ch, x in bare.items()}
        self.tree = PieceTree(weights, self.ids, bare, n)
        self.entries = entries
        self.ways: dict[str, list] = {}  # of a few words whose paths were taken last
        self._forget()

    def _forget(self) -> None:
        """Start the table of words anew: place of each word, probabilities of its best path and of the others, ids of the best."""
        self.place = _Places()
        self.names, self.size = [], np.zeros(0, np.int32)  # words with their marks
        self.p, self.q, self.log_p, self.plain = (np.zeros(0, t) for t in (float, float, float, bool))
        self.best_ids: list[bytes] = []

    def byte_ids(self, ch: str) -> list[int]:
        return [self.bytes[b] for b in ch.encode("utf-8", "surrogatepass")]

    @staticmethod
    def spell(key: str) -> str:
        """A word with its mark; a key that starts with a line feed has none."""
        return key if key[:1] == "\n" else MARK + key

    def lattice(self, s: str) -> tuple[list[list[tuple[int, float]]], list[int], float]:
        """Of one word, in logarithms: per place its (end, probability of going there) ways, the best way's end, and the log-probability of the best path."""
        get, n = self.log_w.get, len(s)
        ways, total, best, end = [[] for _ in range(n)], [0.0] * (n + 1), [0.0] * (n + 1), [0] * n
        for i in range(n - 1, -1, -1):
            found = [(j, x) for j in range(i + 1, min(n, i + self.longest) + 1) if (x := get(s[i:j])) is not None]
            if s[i] not in self.ids:
                found.append((i + 1, self.log_byte * len(s[i].encode("utf-8", "surrogatepass"))))
            sums = [x + total[j] for j, x in found]
            top = max(sums)
            total[i] = top + math.log(sum([math.exp(x - top) for x in sums]))
            best[i], end[i] = max([(x + best[j], j) for j, x in found])
            ways[i] = [(j, math.exp(x - total[i])) for (j, _), x in zip(found, sums)]
        return ways, end, best[0] - total[0]

    def path_ids(self, s: str, path) -> list[int]:
        out = []
        for i, j in zip(path, path[1:]):
            p = s[i:j]
            out.extend([self.ids[p]] if p in self.ids else self.byte_ids(p))
        return out

    def path_ends(self, s: str, ids) -> list[int]:
        """Where the pieces of a path end; bytes of one letter count as one piece."""
        out, i, k = [], 0, 0
        while k < len(ids):
            byte = ids[k] in self.byte_of
            k += len(s[i].encode("utf-8", "surrogatepass")) if byte else 1
            i += 1 if byte else len(self.pieces[ids[k - 1]])
            out.append(i)
        return out

    def _left(self, s: str, taken) -> tuple[list, list, list]:
        """(ways, nodes, mass): the tree of taken paths (node 0: the word's start), and each node's chance of a path not taken."""
        if s not in self.ways:
            if len(self.ways) >= 500:
                self.ways.clear()
            self.ways[s] = self.lattice(s)[0]
        ways = self.ways[s]
        nodes, places = [{}], [0]
        for ids in taken:
            at = 0
            for j in self.path_ends(s, np.frombuffer(ids, "<i4").tolist()):
                if j not in nodes[at]:
                    nodes[at][j] = len(nodes)
                    nodes.append({})
                    places.append(j)
                at = nodes[at][j]
        mass = [0.0] * len(nodes)
        for k in range(len(nodes) - 1, -1, -1):  # children stand behind their parents
            if places[k] < len(s):
                mass[k] = sum([q * (mass[nodes[k][j]] if j in nodes[k] else 1.0) for j, q in ways[places[k]]])
        return ways, nodes, mass

    def mass_left(self, s: str, taken) -> float:
        """Probability of the paths of word `s` that are not in `taken`."""
        return self._left(s, taken)[2][0]

    def draw_other(self, s: str, taken, rng) -> tuple[bytes, float]:
        """(ids, log-probability) of a path of word `s` drawn from those not in `taken` (at least one is left)."""
        ways, nodes, mass = self._left(s, taken)
        path, log_p, node = [0], 0.0, 0
        while path[-1] < len(s):
            here = nodes[node] if node is not None else {}
            options = [(j, q, q * (mass[here[j]] if j in here else 1.0)) for j, q in ways[path[-1]]]
            u = rng.random() * sum([x for _, _, x in options])
            for j, q, x in options:
                if x > 0:
                    last = j, q
                    if u < x:
                        break
                    u -= x
            log_p += math.log(last[1]) if last[1] > 0 else -745.0
            path.append(last[0])
            node = here.get(last[0])
        return np.array(self.path_ids(s, path), "<i4").tobytes(), log_p

    def learn(self) -> None:
        """Put the words that wait for it into the table."""
        keys, self.place.fresh = self.place.fresh, []
        spelled = [key if key[:1] == "\n" else MARK + key for key in keys]
        p, q, log_p, ids = np.empty(len(keys)), np.empty(len(keys)), np.empty(len(keys)), [b""] * len(keys)
        size = np.fromiter(map(len, spelled), np.int32, len(keys))
        letters = self.tree.letter[np.frombuffer("".join(spelled).encode("utf-32-le", "surrogatepass"), np.uint32)]
        plain = (size <= PLAIN_LENGTH) & np.logical_and.reduceat(letters > 0, np.cumsum(size) - size)
        some = np.flatnonzero(plain)
        some = some[np.argsort(size[some], kind="stable")]
        for s in range(0, len(some), SIDE_BY_SIDE):
            part = some[s: s + SIDE_BY_SIDE]
            x = WordLattices(self.tree, [spelled[i] for i in part.tolist()])
            column = x.column
            p[part], q[part], plain[part] = x.p[column], x.q[column], x.sound[column]
            for i, y in zip(part.tolist(), x.paths(column)[0]):
                ids[i] = y
        with np.errstate(divide="ignore", invalid="ignore"):
            log_p[:] = np.log(p)
        for i in np.flatnonzero(~plain).tolist():
            _, end, d = self.lattice(spelled[i])
            path = [0]
            while path[-1] < len(spelled[i]):
                path.append(end[path[-1]])
            p[i], q[i], log_p[i], ids[i] = math.exp(d), -math.expm1(min(0.0, d)), d, np.array(self.path_ids(spelled[i], path), "<i4").tobytes()
        self.names.extend(spelled)
        self.size = np.concatenate([self.size, size])
        self.best_ids.extend(ids)
        self.p, self.q, self.log_p, self.plain = (np.concatenate(x) for x in ((self.p, p), (self.q, q), (self.log_p, log_p), (self.plain, plain)))

    @staticmethod
    def words_of(norm: str) -> list[str]:
        """Keys of the words of a text in the model's own form; marks that follow each other belong to one word."""
        if not norm:
            return []
        keys = norm[1:].replace("\n", MARK + "\n").split(MARK)
        if MARK + MARK not in norm:
            return keys
        out, run = [], 0  # empty keys are marks that belong to the next word
        for k, key in enumerate(keys):
            if key == "" and k + 1 < len(keys) and keys[k + 1][:1] != "\n":
                run += 1
            else:
                out.append(MARK * run + key)
                run = 0
        return out

    def normal(self, text: str | None) -> str:
        """The model's own form of a text, with its first mark."""
        norm = self.processor.normalize(text or "")
        return norm if not norm or norm.startswith(MARK) else MARK + norm

    def _draw_pool(self, places: np.ndarray, seeds: np.ndarray) -> tuple[list[bytes], np.ndarray]:
        """(ids, log-probabilities) for each word's place and seed: a path other than the word's best one."""
        out, logs = [b""] * len(places), np.zeros(len(places))
        plain = self.plain[places]
        # Draws of the same word stand together and share its lattice.
        some = np.flatnonzero(plain)
        some = some[np.lexsort((places[some], self.size[places[some]]))]
        first = np.flatnonzero(np.diff(places[some], prepend=-1))
        for s in range(0, len(first), SIDE_BY_SIDE):
            a, b = first[s], first[s + SIDE_BY_SIDE] if s + SIDE_BY_SIDE < len(first) else len(some)
            heads, part = first[s: s + SIDE_BY_SIDE], some[a:b]
            x = WordLattices(self.tree, [self.names[i] for i in places[some[heads]].tolist()])
            found, logs[part] = x.paths(np.repeat(x.column, np.diff(np.r_[heads, b])), seeds[part].astype(U))
            for k, ids in zip(part.tolist(), found):
                out[k] = ids
        for k in np.flatnonzero(~plain).tolist():
            at = int(places[k])
            out[k], logs[k] = self.draw_other(self.names[at], [self.best_ids[at]], np.random.Generator(np.random.SFC64(int(seeds[k]))))
        return out, logs

    def sample_many(self, texts, keys, samples: int = SAMPLES) -> list[list[tuple[bytes, float, float, float]]]:
        return self.sample_normal(list(map(self.normal, texts)), keys, samples)

    def sample_normal(self, norms, keys, samples: int = SAMPLES) -> list[list[tuple[bytes, float, float, float]]]:
        """Of each text in the model's own form up to `samples` distinct segmentations, best perturbed score first: (ids, log-probability, perturbed score, inclusion)."""
        words = list(map(self.words_of, norms))
        if len(self.best_ids) > self.entries:
            self._forget()
        places = [np.fromiter(map(self.place.__getitem__, ws), np.int64, len(ws)) for ws in words]
        if self.place.fresh:
            try:
                self.learn()
            except BaseException:
                self._forget()  # places without an entry must not stay
                raise
        rows = []
        for ws, at, key in zip(words, places, keys):
            rng = np.random.Generator(np.random.SFC64(xxhash.xxh3_64_intdigest(key)))
            rows.append(_Search(at, rng))
            if not ws:
                rows[-1].value = -math.inf
        for turn in range(samples):
            pool, waiting, done = [(np.zeros(0, np.int64),) * 2], [], 0
            for row, ws in zip(rows, words):
                if not ws or (turn and row.value == -math.inf):
                    continue
                p, n = self.p[row.at], len(ws)
                if turn:  # the open set with the highest score: leave its path at word i
                    top = max(row.open, key=lambda o: o[0].max())
                    k = int(top[0].argmax())
                    top[0][k] = -math.inf
                    (over, logs, others), at, gone = top[1:]
                    i = at + k
                    own = over.get(i) or self.best_ids[row.at[i]]
                    excluded = dict(gone) if k == 0 else {own: float(logs[i])}
                    over = {k: x for k, x in over.items() if k < i}
                    logs, others = logs.copy(), others.copy()
                    logs[i:], others[i:] = self.log_p[row.at[i:]], self.q[row.at[i:]]
                    if list(excluded) == [self.best_ids[row.at[i]]]:
                        ask = [i]
                    else:
                        ask = []
                        over[i], logs[i] = self.draw_other(self.spell(ws[i]), excluded, row.rng)
                        others[i] = -math.expm1(min(logs[i], -1e-300))
                    score, start = row.value, i + 1
                else:
                    over, logs, others, ask, excluded, i = {}, self.log_p[row.at], self.q[row.at], [], None, 0
                    score, start = float(row.rng.gumbel()), 0
                ask = np.r_[np.array(ask, np.int64), start + np.flatnonzero(row.rng.random(n - start) >= p[start:])]
                pool.append((row.at[ask], row.rng.integers(0, 1 << 63, len(ask), np.int64)))
                waiting.append((row, ws, (over, logs, others), ask, excluded, i, score))
            drawn, drawn_logs = self._draw_pool(*map(np.concatenate, zip(*pool)))
            for row, ws, path, ask, excluded, i, score in waiting:
                over, logs, others = path
                here = slice(done, done + len(ask))
                done = here.stop
                over.update(zip(ask.tolist(), drawn[here]))
                logs[ask] = drawn_logs[here]
                others[ask] = -np.expm1(np.minimum(logs[ask], -1e-300))
                own = over.get(i) or self.best_ids[row.at[i]]
                row.found.append((path, float(logs.sum()), score))
                self._split(row, ws, path, i, {**(excluded or {}), own: float(logs[i])}, score, turn + 1 == samples)
        return [self._results(row) for row in rows]

    def _split(self, row: _Search, words: list[str], path, at: int, gone: dict, ceiling: float, last: bool) -> None:
        """Open the sets of paths that share the path's words before i and depart at i, for each i from `at` on.

        After the `last` path only the best score of these sets is asked for: it is the score of their union.
        """
        _, logs, others = path
        left = others[at:]
        if len(gone) > 1:
            left = left.copy()
            left[0] = self.mass_left(self.spell(words[at]), gone)
        before = np.cumsum(logs)
        before -= logs
        with np.errstate(divide="ignore"):
            mu = before[at:] + np.log(left)
            if last:
                mu = np.logaddexp.reduce(mu, keepdims=True)
        v = -np.logaddexp(-ceiling, -(mu + row.rng.gumbel(size=len(mu))))
        v[mu == -np.inf] = -np.inf
        row.open.append([v, path, at, gone])
        row.value = max([float(o[0].max()) for o in row.open])

    def _results(self, row: _Search) -> list[tuple[bytes, float, float, float]]:
        if not len(row.at):
            return [(b"", 0.0, float(row.rng.gumbel()), 1.0)]
        out, best = [], list(map(self.best_ids.__getitem__, row.at.tolist()))
        for (over, _, _), lp, score in row.found:
            ids = best
            if over:
                ids = list(best)
                for i, x in over.items():
                    ids[i] = x
            # The first path left out sets the threshold of inclusion.
            out.append((b"".join(ids), lp, score, 1.0 if row.value == -math.inf else -math.expm1(-math.exp(min(700.0, lp - row.value)))))
        return out

    def sample(self, text: str | None, key: str, samples: int = SAMPLES) -> list[tuple[bytes, float, float, float]]:
        return self.sample_many([text], [key], samples)[0]

    def joined(self, ids: list[int]) -> str:
        """Pieces of ids side by side, byte pieces joined into UTF-8."""
        return b"".join(map(self.written.__getitem__, ids)).decode("utf-8", "replace")

    def gives(self, values: np.ndarray, norm: str) -> bool:
        """Whether ids give a text in the model's own form."""
        long = self.long[values]
        end = np.cumsum(long)
        places = np.repeat(self.start[values] - (end - long), long)
        places += np.arange(len(places))
        return self.flat[places].tobytes() == norm.encode("utf-8", "surrogatepass") or self.joined(values.tolist()) == norm

    def decode(self, ids) -> str:
        """Text of ids: marks become spaces, the mark put before the text goes."""
        text = self.joined(list(ids)).replace(MARK, " ")
        return text[1:] if text.startswith(" ") else text


@functools.cache
def worker_lattice(model: str, sharpness: float) -> PieceLattice:
    """One lattice for all tasks of a Python worker."""
    return PieceLattice(model, sharpness)


HELD.append(worker_lattice)


def _portions(batch: pa.RecordBatch):
    """(ids, texts) of at most BATCH_ROWS rows and about BATCH_CHARS characters; longer texts alone."""
    ids, texts, size = [], [], 0
    for ident, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
        if texts and (len(texts) >= BATCH_ROWS or size + len(text or "") > BATCH_CHARS):
            yield ids, texts
            ids, texts, size = [], [], 0
        ids.append(ident)
        texts.append(text)
        size += len(text or "")
    if texts:
        yield ids, texts


def _sampled(model: str, samples: int, sharpness: float, digest: bool, kind: pa.DataType):
    names = ["doc_id", "sample", "n_tokens", "ids_crc32" if digest else "ids", "log_prob", "perturbed", "inclusion", *(["decodes"] if digest else [])]
    types = [kind, pa.int32(), pa.int64(), pa.int64() if digest else pa.list_(pa.int32()), pa.float64(), pa.float64(), pa.float64(), *([pa.bool_()] if digest else [])]

    def run(batches):
        lattice = worker_lattice(model, sharpness)
        for b in batches:
            for idents, texts in _portions(b):
                rows = []
                with without_cycles():
                    norms = list(map(lattice.normal, texts))
                    for ident, norm, found in zip(idents, norms, lattice.sample_normal(norms, list(map(str, idents)), samples)):
                        for k, (ids, lp, score, inclusion) in enumerate(found):
                            values = np.frombuffer(ids, "<i4")
                            more = (zlib.crc32(ids), lp, score, inclusion, lattice.gives(values, norm)) if digest else (values, lp, score, inclusion)
                            rows.append((ident, k, len(values), *more))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names)

    return tidy(run, worker_lattice)


def sample_segmentations(df: DataFrame, model: str, samples: int = SAMPLES, sharpness: float = SHARPNESS, text: str = "text", ident: str = "doc_id", digest: bool = False) -> DataFrame:
    """(ident, sample, n_tokens, ids, log_prob, perturbed, inclusion), up to `samples` rows a document.

    With `digest`, ids_crc32 instead of ids, and `decodes`: whether the ids give the text, in the model's own form, back.
    """
    bounded_batches(df.sparkSession)
    kind = df.schema[ident].dataType.simpleString()
    arrow = {"string": pa.string(), "int": pa.int32()}.get(kind, pa.int64())
    schema = f"doc_id {kind}, sample int, n_tokens long, {'ids_crc32 long' if digest else 'ids array<int>'}, log_prob double, perturbed double, inclusion double"
    schema += ", decodes boolean" if digest else ""
    rows = df.select(F.col(ident).alias("doc_id"), F.col(text).alias("_text")).mapInArrow(_sampled(model, samples, sharpness, digest, arrow), schema)
    return rows.withColumnRenamed("doc_id", ident)


def encode(df: DataFrame, model: str, text: str = "text", output: str = "ids") -> DataFrame:
    """Adds the library's own encoding of `text` (null: empty) as an array of ids."""

    def run(batches):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model)
        for b in batches:
            ids = sp.encode([t or "" for t in b.column(text).to_pylist()], num_threads=1)
            yield b.append_column(output, pa.array(ids, pa.list_(pa.int32())))

    return df.mapInArrow(run, f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in df.schema)}, `{output}` array<int>")


def decode(df: DataFrame, model: str, ids: str = "ids", output: str = "text") -> DataFrame:
    """Adds the text of an array of ids (null: empty)."""

    def run(batches):
        lattice = worker_lattice(model, SHARPNESS)
        for b in batches:
            yield b.append_column(output, pa.array([lattice.decode(x or []) for x in b.column(ids).to_pylist()], pa.string()))

    return df.mapInArrow(run, f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in df.schema)}, `{output}` string")
