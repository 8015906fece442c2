"""Removal of long byte strings that an earlier document has, by suffix sorting.

Every string of `length` bytes contains whole one of its text's anchors: the grams of `GRAM` bytes with the least hash of some
`length - GRAM + 1` neighbouring grams. Equal strings have equal anchors, so:

1. anchors are counted over the corpus; two bitmaps of fixed size mark those seen twice or more, and the hot ones;
2. a repeated anchor sends a 64-bit hash of its surroundings (all strings around it) to a task of its own; a third bitmap marks
   the anchors whose surroundings differ. Where all are alike, the earliest document keeps them, and no text has to move;
3. an anchor with different surroundings sends them to a task of its hash; equal surroundings of one partition collapse to the
   earliest document first. Around hot anchors every string goes to a task of its own hash instead, so that the many
   different surroundings of a common phrase do not meet in one task;
4. a task sorts the strings around its anchors by deep-shallow sorting: they are bucketed by anchor and place beside it (equal
   strings agree in both), multikey quicksort on 8-byte letters takes the buckets down to a shallow depth, then blind tries
   order the groups that still agree; strings equal over `length` bytes stand together, and all but those of the least doc_id
   are removed.

Defined results: a null text has no bytes; a null doc_id neither removes nor is removed; rows of one doc_id do not remove from
each other; an empty table gives an empty result. Ids are integers.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import block_bits, bounded_batches, maybe_broadcast, stash, tidy
from .ngram_join import _blocks, mix64

LENGTH, GRAM = 50, 32
#: Bits of each bitmap of anchors; an anchor takes two places.
MAP_BITS = 27
#: Anchors that so many documents have are hot: their surroundings would fill a task's memory.
HOT = 65_536
#: Bytes of text worked on at a time, and records gathered before a partition sends them.
SLICE, FLUSH = 1 << 18, 100_000
#: In place of an anchor's offset: a single string, or an anchor that stands for surroundings that are alike everywhere.
ALONE, ALIKE = 255, 254
U = np.uint64
_BASE = U(0x9E3779B97F4A7C15)
EMPTY_SHA = hashlib.sha256(b"").hexdigest()


def _sliding(a: np.ndarray, width: int, pick) -> np.ndarray:
    """pick (minimum or maximum) over a[i : i + width], for every full window."""
    done, m = 1, a
    while done * 2 <= width:
        m = pick(m[:-done], m[done:])
        done *= 2
    return m if done == width else pick(m[: len(a) - width + 1], m[width - done: width - done + len(a) - width + 1])


def _gram_hashes(data: np.ndarray, gram: int) -> np.ndarray:
    """Hash of every gram, by doubling."""
    h, power, width = data.astype(U) + U(1), _BASE, 1
    out, out_width, p = None, 0, None
    g = gram
    while True:
        if g & 1:
            if out is None:
                out, out_width = h, width
            else:  # the grams so far, then `width` bytes more
                n = len(data) - out_width - width + 1
                out = out[:n] * power + h[out_width: out_width + n]
                out_width += width
        g >>= 1
        if not g:
            return mix64(out)
        h = h[: len(h) - width] * power + h[width:]
        power = power * power
        width *= 2


def anchors(data: np.ndarray, ends: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """(places, hashes) of the anchors of the texts that lie one after another in `data` and end at `ends`."""
    n = len(data)
    if n < length:
        return np.zeros(0, np.int64), np.zeros(0, U)
    with np.errstate(over="ignore"):
        h = _gram_hashes(data, gram)
    h |= U(1)
    crosses = np.zeros(n + 1, np.int32)  # +1 at the first gram that would run over an end
    starts = np.r_[0, ends[:-1]]
    np.add.at(crosses, np.maximum(ends - gram + 1, starts), 1)
    np.add.at(crosses, ends, -1)
    good = np.cumsum(crosses)[: len(h)] == 0
    h[~good] = U(0xFFFFFFFFFFFFFFFF)
    width = length - gram + 1
    least = _sliding(h, width, np.minimum)
    crosses[:] = 0
    np.add.at(crosses, np.maximum(ends - length + 1, starts), 1)
    np.add.at(crosses, ends, -1)
    least[np.cumsum(crosses)[: len(least)] != 0] = 0
    padded = np.zeros(len(h) + width - 1, U)
    padded[width - 1: width - 1 + len(least)] = least
    at = np.flatnonzero((_sliding(padded, width, np.maximum) == h) & good)
    return at, h[at]


def _slices(batches):
    """(ids, ties, data, starts, ends): the rows' texts in pieces of about SLICE bytes; longer texts alone."""
    ids, ties, texts, size = [], [], [], 0

    def pack():
        lengths = np.array([len(t) for t in texts], np.int64)
        ends = np.cumsum(lengths)
        return np.array(ids, np.int64), np.array(ties, np.int64), np.frombuffer(b"".join(texts), np.uint8), ends - lengths, ends

    for b in batches:
        for i, tie, text in zip(*(c.to_pylist() for c in b.columns)):
            data = text.encode("utf-8", "surrogatepass")
            if size and size + len(data) > SLICE:
                yield pack()
                ids, ties, texts, size = [], [], [], 0
            ids.append(i)
            ties.append(tie)
            texts.append(data)
            size += len(data)
    if texts:
        yield pack()


def pack_sorted(tokens: np.ndarray) -> bytes:
    """Sorted 32-bit values as packed differences, byte by byte: their upper bytes are mostly zero."""
    step = np.diff(tokens.astype("<u4"), prepend=np.uint32(0))
    return _zip(np.ascontiguousarray(step.view(np.uint8).reshape(-1, 4).T).tobytes())


def unpack_sorted(data: bytes) -> np.ndarray:
    step = np.ascontiguousarray(np.frombuffer(_unzip(data), np.uint8).reshape(4, -1).T).view("<u4").ravel()
    return np.cumsum(step, dtype=np.uint64).astype(np.uint32)


def _anchor_pieces(bits: int, length: int):
    """(block, tokens, counts) of a partition: how many of its documents have an anchor, summed up before it is sent."""

    def flush(parts):
        h, count = np.unique(np.concatenate(parts), return_counts=True)
        count = np.minimum(count, 0xFFFFFFFF).astype("<u4")
        rows = [(block, pack_sorted(np.frombuffer(low, "<u4")), _zip(n)) for block, low, n in _blocks(h, bits, count)]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.binary()))], ["block", "tokens", "counts"])

    def run(batches):
        parts, n = [], 0
        for _, _, data, starts, ends in _slices(batches):
            at, h = anchors(data, ends, length)
            if len(at):
                doc = np.searchsorted(ends, at, "right")
                order = np.lexsort((h, doc))
                doc, h = doc[order], h[order]
                h = h[np.r_[True, (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])]]
                parts.append(h)
                n += len(h)
            if n >= 20 * FLUSH:
                yield flush(parts)
                parts, n = [], 0
        if n:
            yield flush(parts)

    return tidy(run)


def _anchor_segments(bits: int, levels):
    """Of one block, for each level the bitmap segment of the anchors that so many documents have; two places an anchor."""
    width = MAP_BITS - bits

    def run(key, t):
        tokens = np.concatenate([unpack_sorted(x) for x in t.column("tokens").to_pylist()])
        counts = np.concatenate([np.frombuffer(_unzip(x), "<u4") for x in t.column("counts").to_pylist()]).astype(np.int64)
        order = np.argsort(tokens, kind="stable")
        tokens, counts = tokens[order], counts[order]
        first = np.flatnonzero(np.r_[True, tokens[1:] != tokens[:-1]])
        count = np.add.reduceat(counts, first)
        maps = []
        for level in levels:
            bitmap = np.zeros(1 << width, bool)
            much = tokens[first[count >= level]]
            bitmap[much >> np.uint32(32 - width)] = True
            bitmap[much & np.uint32((1 << width) - 1)] = True
            maps.append(np.packbits(bitmap).tobytes() if len(much) else None)
        return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), **{f"map{k}": pa.array([m], pa.binary()) for k, m in enumerate(maps)}})

    return run


def _probe(h: np.ndarray, bitmap: np.ndarray, bits: int) -> np.ndarray:
    width = MAP_BITS - bits
    base = (h >> U(64 - bits) << U(width)).astype(np.int64)
    token = (h >> U(32 - bits)) & U(0xFFFFFFFF)
    out = np.ones(len(h), bool)
    for place in (token >> U(32 - width), token & U((1 << width) - 1)):
        at = base | place.astype(np.int64)
        out &= (bitmap[at >> 3] >> (7 - (at & 7)).astype(np.uint8) & 1).astype(bool)
    return out


def _row_hash(rows: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit hash of each padded row and its length, the row as words)."""
    pad = -(rows.shape[1] + 1) % 8
    words = np.ascontiguousarray(np.concatenate([rows, size[:, None].astype(np.uint8), np.zeros((len(rows), pad), np.uint8)], axis=1)).view(">u8").astype(U)
    with np.errstate(over="ignore"):
        h = np.zeros(len(rows), U)
        for k in range(words.shape[1]):
            h = mix64(h * _BASE + words[:, k])
    return h, words


def _text_rows(data: np.ndarray, first: np.ndarray, size: np.ndarray, width: int) -> np.ndarray:
    """The `size` bytes from `first` on, in rows of `width` bytes filled up with zeros."""
    column = first[:, None] + np.arange(width)
    return np.where(np.arange(width) < size[:, None], data[np.minimum(column, len(data) - 1)], 0).astype(np.uint8)


def _surrounding_hashes(repeated, bits: int, length: int):
    """(block, tokens, hashes) of a partition: of each repeated anchor the least and the largest hash of its surroundings."""

    def flush(parts):
        h, s = (np.concatenate(x) for x in zip(*parts))
        order = np.lexsort((s, h))
        h, s = h[order], s[order]
        new = np.r_[True, h[1:] != h[:-1]]
        head = np.maximum.accumulate(np.where(new, np.arange(len(h)), 0))
        keep = new | (np.r_[new[1:], True] & (s != s[head]))
        rows = [(block, pack_sorted(np.frombuffer(low, "<u4")), x) for block, low, x in _blocks(h[keep], bits, s[keep].astype("<u8"))]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.binary()))], ["block", "tokens", "hashes"])

    def run(batches):
        parts, n = [], 0
        for _, _, data, starts, ends in _slices(batches):
            at, h = anchors(data, ends, length)
            again = _probe(h, repeated.value, bits)
            at, h = at[again], h[again]
            if len(at):
                doc = np.searchsorted(ends, at, "right")
                first, last = np.maximum(starts[doc], at + GRAM - length), np.minimum(ends[doc], at + length)
                parts.append((h, _row_hash(_text_rows(data, first, last - first, 2 * length - GRAM), last - first)[0]))
                n += len(h)
            if n >= 4 * FLUSH:
                yield flush(parts)
                parts, n = [], 0
        if n:
            yield flush(parts)

    return tidy(run)


def _mixed_segments(bits: int):
    """Of one block the bitmap segment of the anchors whose surroundings differ; two places an anchor."""
    width = MAP_BITS - bits

    def run(key, t):
        tokens = np.concatenate([unpack_sorted(x) for x in t.column("tokens").to_pylist()])
        hashes = np.concatenate([np.frombuffer(x, "<u8") for x in t.column("hashes").to_pylist()])
        order = np.argsort(tokens, kind="stable")
        tokens, hashes = tokens[order], hashes[order]
        first = np.flatnonzero(np.r_[True, tokens[1:] != tokens[:-1]])
        mixed = tokens[first[np.minimum.reduceat(hashes, first) != np.maximum.reduceat(hashes, first)]]
        bitmap = np.zeros(1 << width, bool)
        bitmap[mixed >> np.uint32(32 - width)] = True
        bitmap[mixed & np.uint32((1 << width) - 1)] = True
        return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), "map0": pa.array([np.packbits(bitmap).tobytes() if len(mixed) else None], pa.binary())})

    return run


class _Records:
    """Surroundings of anchors (or single strings): block, document, tie, place, anchor's offset, length, bytes in a padded row."""

    def __init__(self, width: int):
        self.width, self.parts, self.n = width, [], 0

    def add(self, block, doc, tie, place, off, size, data, first):
        if len(block):
            rows = _text_rows(data, first, size, self.width)
            self.parts.append((block, doc, tie, place.astype(np.int32), off.astype(np.uint8), size.astype(np.uint8), rows))
            self.n += len(block)

    def add_alike(self, block, doc, tie, place, size, h):
        """The anchor's hash stands for the surroundings; the last byte tells such a row from a text."""
        if len(block):
            rows = np.zeros((len(block), self.width), np.uint8)
            rows[:, :8] = h.astype("<u8").view(np.uint8).reshape(-1, 8)
            rows[:, -1] = 255
            self.parts.append((block, doc, tie, place.astype(np.int32), np.full(len(block), ALIKE, np.uint8), size.astype(np.uint8), rows))
            self.n += len(block)

    def take(self):
        out = [np.concatenate(c) for c in zip(*self.parts)]
        self.parts, self.n = [], 0
        return out


def _zip(data: bytes) -> bytes:
    return len(data).to_bytes(4, "little") + pa.compress(data, codec="zstd", asbytes=True)


def _unzip(data: bytes) -> bytes:
    return pa.decompress(data[4:], int.from_bytes(data[:4], "little"), codec="zstd", asbytes=True)


def _same_rows(rows: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, new): rows sorted by bytes and length, and where another row begins."""
    h, words = _row_hash(rows, size)
    order = np.argsort(h, kind="stable")
    w = words[order]
    return order, np.r_[True, (w[1:] != w[:-1]).any(1)] if len(w) else np.zeros(0, bool)


def _least_of_group(order: np.ndarray, new: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Per row the least doc of its group."""
    out = np.empty(len(doc), np.int64)
    if len(doc):
        first = np.flatnonzero(new)
        out[order] = np.repeat(np.minimum.reduceat(doc[order], first), np.diff(np.r_[first, len(doc)]))
    return out


def _pack_spans(doc, tie, start, end):
    """Arrow columns of merged spans, a row per (doc, tie)."""
    order = np.lexsort((start, tie, doc))
    doc, tie, start, end = doc[order], tie[order], start[order], end[order]
    new = np.r_[True, (doc[1:] != doc[:-1]) | (tie[1:] != tie[:-1])]
    group = np.cumsum(new) - 1
    shift = group.astype(np.int64) << 33  # spans of one group lie behind those of the group before
    reach = np.maximum.accumulate(end + shift)
    cut = np.r_[True, (start + shift)[1:] > reach[:-1]]
    first = np.flatnonzero(cut)
    starts, ends = start[first], (reach[np.r_[first[1:] - 1, len(reach) - 1]] - shift[first])
    heads = np.flatnonzero(new)
    offsets = np.r_[np.searchsorted(first, heads), len(first)].astype(np.int32)
    lists = [pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(x.astype(np.int32))) for x in (starts, ends)]
    return [pa.array(doc[heads]), pa.array(tie[heads]), *lists]


def _surroundings(repeated, hot, mixed, bits: int, length: int):
    """Pieces (block, kind, doc, tie, place, off, size, data) of a partition; kind 1 holds spans that are settled already."""
    names = ["block", "kind", "doc", "tie", "place", "off", "size", "data"]
    types = [pa.int32(), pa.int8()] + [pa.binary()] * 6

    def flush(records):
        block, doc, tie, place, off, size, rows = records.take()
        order, new = _same_rows(rows, size)
        least = _least_of_group(order, new, doc)
        later = doc > least
        out = []
        if later.any():
            d, t, s, e = doc[later], tie[later], place[later].astype(np.int64), place[later].astype(np.int64) + size[later]
            by = (mix64(d.view(U)) >> U(64 - bits)).astype(np.int64)
            order = np.argsort(by, kind="stable")
            for part in np.split(order, np.flatnonzero(np.diff(by[order])) + 1):
                out.append((int(by[part[0]]), 1, _zip(d[part].tobytes()), _zip(t[part].tobytes()), _zip(s[part].astype("<i4").tobytes()), None, _zip(e[part].astype("<i4").tobytes()), None))
        keep = np.flatnonzero(~later)
        # By block, and in it by the text from the anchor on: like surroundings side by side pack well.
        lead = np.where(off[keep] >= ALIKE, 0, off[keep]).astype(np.int64)
        wide = np.where(off == ALIKE, 8, size)
        column = np.minimum(lead[:, None] + np.arange(8), rows.shape[1] - 1)
        text = np.ascontiguousarray(rows[keep[:, None], column]).view(">u8").ravel().astype(U)
        keep = keep[np.lexsort((text, block[keep]))]
        for part in np.split(keep, np.flatnonzero(np.diff(block[keep])) + 1):
            flat = rows[part][np.arange(rows.shape[1]) < wide[part][:, None]]
            out.append((int(block[part[0]]), 0, _zip(doc[part].tobytes()), _zip(tie[part].tobytes()), _zip(place[part].tobytes()), off[part].tobytes(), size[part].tobytes(), _zip(flat.tobytes())))
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names)

    def run(batches):
        records = _Records(2 * length - GRAM)
        for ids, ties, data, starts, ends in _slices(batches):
            at, h = anchors(data, ends, length)
            again = _probe(h, repeated.value, bits)
            at, h = at[again], h[again]
            if not len(at):
                continue
            doc = np.searchsorted(ends, at, "right")
            first, last = np.maximum(starts[doc], at + GRAM - length), np.minimum(ends[doc], at + length)
            differ = _probe(h, mixed.value, bits)
            k = ~differ
            records.add_alike((h[k] >> U(64 - bits)).astype(np.int64), ids[doc[k]], ties[doc[k]], first[k] - starts[doc[k]], last[k] - first[k], h[k])
            common = _probe(h, hot.value, bits) & differ
            k = differ & ~common
            records.add((h[k] >> U(64 - bits)).astype(np.int64), ids[doc[k]], ties[doc[k]], first[k] - starts[doc[k]], at[k] - first[k], last[k] - first[k], data, first[k])
            k = np.flatnonzero(common)
            for s in range(0, len(k), 4096):  # each string around a hot anchor by itself
                part = k[s: s + 4096]
                count = np.maximum(0, last[part] - first[part] - length + 1)
                start = np.repeat(first[part], count) + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
                start, pick = np.unique(start, return_index=True)
                d = np.repeat(doc[part], count)[pick]
                with np.errstate(over="ignore"):
                    w = np.zeros(len(start), U)
                    for c in range(length):
                        w = w * _BASE + data[start + c].astype(U)
                full = np.full(len(start), length)
                records.add((mix64(w) >> U(64 - bits)).astype(np.int64), ids[d], ties[d], start - starts[d], np.full(len(start), ALONE), full, data, start)
                if records.n >= FLUSH:
                    yield flush(records)
            if records.n >= FLUSH:
                yield flush(records)
        if records.n:
            yield flush(records)

    return tidy(run)


class BlindTrie:
    """Trie over windows of one text that stores only where they branch; equal windows share a leaf."""

    __slots__ = ("data", "depth", "root")

    def __init__(self, data: bytes, depth: int):
        self.data, self.depth, self.root = data, depth, None

    def add(self, start: int) -> None:
        """Go down by branching letters only, compare once with the leaf found, then branch where they differ."""
        if self.root is None:
            self.root = [start]
            return
        key = self.data[start: start + self.depth]
        node = self.root
        while isinstance(node, tuple):
            place, ways = node
            way = ways.get(key[place])
            node = way if way is not None else next(iter(ways.values()))
        other = self.data[node[0]: node[0] + self.depth]
        if other == key:
            node.append(start)
            return
        differ = self.depth - (((int.from_bytes(key) ^ int.from_bytes(other)).bit_length() + 7) // 8)
        parent, node = None, self.root
        while isinstance(node, tuple) and node[0] < differ:
            parent, node = node, node[1][key[node[0]]]
        if isinstance(node, tuple) and node[0] == differ:
            node[1][key[differ]] = [start]
            return
        branch = (differ, {key[differ]: [start], other[differ]: node})
        if parent is None:
            self.root = branch
        else:
            parent[1][key[parent[0]]] = branch

    def groups(self):
        """Lists of equal windows, in byte order."""
        stack = [self.root]
        while stack:
            node = stack.pop()
            if isinstance(node, tuple):
                stack.extend(w for _, w in sorted(node[1].items(), reverse=True))
            elif node is not None:
                yield node


def deep_shallow_sort(text: np.ndarray, starts: np.ndarray, depth: int, shallow: int = 16, bucket: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(order, new): indices into `starts` sorted by (bucket, the `depth` bytes there), and where a window differs from the one before.

    Multikey quicksort takes eight bytes as one letter: a round splits every open group by the letter of its middle member
    into less, equal and greater, and only the equal part goes on to the next letter. Groups that agree on `shallow` bytes are
    compared with their first member at once; those that do not wholly agree go to a blind trie.
    """
    n = len(starts)
    padded = np.zeros(len(text) + depth + 8, np.uint8)
    padded[: len(text)] = text
    letters = np.zeros(len(padded) - 7, U)
    for k in range(8):
        letters = letters << U(8) | padded[k: len(letters) + k].astype(U)
    order = np.arange(n) if bucket is None else np.argsort(bucket, kind="stable")
    new = np.zeros(n, bool)
    if n:
        new[0] = True
        if bucket is not None:
            new[1:] = bucket[order[1:]] != bucket[order[:-1]]
    level = np.zeros(n, np.int64)  # bytes in which the members of a group agree
    some = np.arange(n)  # places of open groups
    while len(some):
        head = np.flatnonzero(new[some])
        size = np.diff(np.r_[head, len(some)])
        group = np.repeat(np.arange(len(head)), size)
        live = ((size > 1) & (level[some[head]] < shallow))[group]
        some, group = some[live], group[live]
        if not len(some):
            break
        head = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
        size = np.diff(np.r_[head, len(some)])
        group = np.repeat(np.arange(len(head)), size)
        letter = letters[starts[order[some]] + level[some]]
        pivot = letter[head + size // 2][group]
        side = (letter >= pivot).astype(np.int64) + (letter > pivot)
        by = np.argsort(group * 3 + side, kind="stable")
        order[some], side = order[some][by], side[by]
        level[some] += 8 * (side == 1)
        new[some[1:]] |= (side[1:] != side[:-1]) & (group[1:] == group[:-1])
    first = np.flatnonzero(new)
    size = np.diff(np.r_[first, n])
    lead = np.repeat(first, size)
    same = np.ones(n, bool)
    for d in range(shallow, depth, 8):
        cut = U(8 * max(0, d + 8 - depth))
        same &= letters[starts[order] + d] >> cut == letters[starts[order[lead]] + d] >> cut
    uneven = np.unique(lead[~same])
    if len(uneven):
        data = padded.tobytes()
        end = dict(zip(first.tolist(), (first + size).tolist()))
        for a in uneven.tolist():
            b = end[a]
            members = order[a:b]
            trie = BlindTrie(data, depth)
            where: dict[int, list[int]] = {}
            for m, s in zip(members.tolist(), starts[members].tolist()):
                if s in where:
                    where[s].append(m)
                else:
                    where[s] = [m]
                    trie.add(s)
            at = a
            for leaf in trie.groups():
                new[at] = True
                for s in leaf:
                    order[at: at + len(where[s])] = where[s]
                    at += len(where[s])
    return order, new


def _settle(length: int):
    """Of one block: spans to remove, a row per document."""

    def run(key, t):
        doc, tie, start, end = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        parts = []
        for kind, d, ti, p, o, s, data in zip(*(t.column(c).to_pylist() for c in ("kind", "doc", "tie", "place", "off", "size", "data"))):
            d, ti, p = _unzip(d), _unzip(ti), _unzip(p)
            if kind:
                doc.append(np.frombuffer(d, np.int64))
                tie.append(np.frombuffer(ti, np.int64))
                start.append(np.frombuffer(p, "<i4").astype(np.int64))
                end.append(np.frombuffer(_unzip(s), "<i4").astype(np.int64))
            else:
                size = np.frombuffer(s, np.uint8)
                rows = np.zeros((len(size), 2 * length - GRAM), np.uint8)
                off = np.frombuffer(o, np.uint8)
                rows[np.arange(rows.shape[1]) < np.where(off == ALIKE, 8, size)[:, None]] = np.frombuffer(_unzip(data), np.uint8)
                rows[off == ALIKE, -1] = 255
                parts.append((np.frombuffer(d, np.int64), np.frombuffer(ti, np.int64), np.frombuffer(p, "<i4").astype(np.int64), off, size, rows))
        if parts:
            d, ti, p, o, s, rows = (np.concatenate(c) for c in zip(*parts))
            order, new = _same_rows(rows, s)
            later = d > _least_of_group(order, new, d)
            doc.append(d[later])
            tie.append(ti[later])
            start.append(p[later])
            end.append(p[later] + s[later])
            # What is left differs; suffixes are sorted where several surroundings share their anchor.
            k = np.flatnonzero(~later & (o < ALIKE))
            d, ti, p, o, s, rows = d[k], ti[k], p[k], o[k].astype(np.int64), s[k].astype(np.int64), rows[k]
            if len(k) > 1:
                gram = rows[np.arange(len(k))[:, None], o[:, None] + np.arange(GRAM)]
                order, new = _same_rows(gram, np.zeros(len(k), np.uint8))
                group = np.empty(len(k), np.int64)
                group[order] = np.cumsum(new) - 1
                k = np.flatnonzero(np.bincount(group)[group] > 1)
                d, ti, p, o, s, rows, group = d[k], ti[k], p[k], o[k], s[k], rows[k], group[k]
            else:
                k = k[:0]
            if len(k):
                text = rows[np.arange(rows.shape[1]) < s[:, None]]
                base = np.cumsum(s) - s
                count = s - length + 1
                owner = np.repeat(np.arange(len(k)), count)
                shift = np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)
                order, new = deep_shallow_sort(text, base[owner] + shift, length, bucket=group[owner] * 256 + shift - o[owner] + 128)
                owner, shift = owner[order], shift[order]
                first = np.flatnonzero(new)
                least = np.repeat(np.minimum.reduceat(d[owner], first), np.diff(np.r_[first, len(owner)]))
                later = d[owner] > least
                owner, shift = owner[later], shift[later]
                doc.append(d[owner])
                tie.append(ti[owner])
                start.append(p[owner] + shift)
                end.append(p[owner] + shift + length)
        doc, tie, start, end = (np.concatenate(x) for x in (doc, tie, start, end))
        if not len(doc):
            return pa.table({"doc": pa.array([], pa.int64()), "tie": pa.array([], pa.int64()), "starts": pa.array([], pa.list_(pa.int32())), "ends": pa.array([], pa.list_(pa.int32()))})
        return pa.Table.from_arrays(_pack_spans(doc, tie, start, end), ["doc", "tie", "starts", "ends"])

    return run


def cut_text(data: bytes, spans: list[tuple[int, int]]) -> tuple[bytes, int, int]:
    """(remaining bytes, removed bytes, maximal removed runs)."""
    kept, at, removed, runs = [], 0, 0, 0
    last = -1
    for s, e in sorted(spans):
        if s > at or last < 0:
            kept.append(data[at:s])
            runs += 1
            removed += e - s
            at = e
        elif e > at:
            removed += e - at
            at = e
        last = at
    kept.append(data[at:])
    return b"".join(kept), removed, runs


def _cut_rows(batches):
    for b in batches:
        out = []
        for i, text, spans in zip(*(c.to_pylist() for c in b.columns)):
            data = text.encode("utf-8", "surrogatepass")
            kept, removed, runs = cut_text(data, [x for part in spans for x in zip(part["starts"], part["ends"])])
            out.append((i, len(data), removed, runs, hashlib.sha256(kept).hexdigest(), kept))
        if out:
            types = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], ["_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])


def _bitmaps(segments: DataFrame, bits: int, count: int) -> list:
    """The segments' bitmaps of fixed size, sent to the tasks."""
    size = 1 << (MAP_BITS - 3 - bits)
    maps = [np.zeros(1 << (MAP_BITS - 3), np.uint8) for _ in range(count)]
    for r in segments.toLocalIterator():
        for k, m in enumerate(maps):
            if r[f"map{k}"] is not None:
                m[r["block"] * size: (r["block"] + 1) * size] = np.frombuffer(r[f"map{k}"], np.uint8)
    return [segments.sparkSession.sparkContext.broadcast(m) for m in maps]


def remove_repeats(df: DataFrame, text: str = "text", ident: str = "doc_id", length: int = LENGTH) -> DataFrame:
    """(ident, n_bytes, n_removed, n_spans, kept_sha256, kept) of every row; kept holds the remaining bytes."""
    spark = df.sparkSession
    bounded_batches(spark)
    bits = block_bits(df, block_bytes=1 << 19)
    docs = df.select(F.col(ident).cast("long").alias("_id"), F.coalesce(F.col(text), F.lit("")).alias("_text"))
    docs = docs.withColumns({"_hash": F.xxhash64("_text"), "_sha": F.sha2("_text", 256)})
    marks = stash(docs.where("_id is not null").select("_id", "_hash", "_sha"), "marks")
    # Whole texts that a smaller doc_id has are settled at once.
    classes = marks.groupBy("_hash", "_sha").agg(F.min("_id").alias("_first"), F.max("_id").alias("_last")).where("_first < _last")
    classes = maybe_broadcast(stash(classes.drop("_last"), "texts"), 100)
    # Only where an id repeats with other texts does a hash of the text have to tell its rows apart.
    several = marks.groupBy("_id").agg(F.min("_hash").alias("lo"), F.max("_hash").alias("hi")).where("lo != hi").select("_id", F.lit(True).alias("_several"))
    several = maybe_broadcast(stash(several, "several"), 16)
    docs = docs.join(classes, ["_hash", "_sha"], "left").join(several, "_id", "left")
    docs = docs.withColumns({
        "_copy": F.coalesce(F.col("_id") > F.col("_first"), F.lit(False)) & (F.octet_length("_text") >= length),
        "_tie": F.when(F.col("_several"), F.col("_hash")).otherwise(F.lit(0).cast("long")),
    }).drop("_first", "_several", "_hash")
    fresh = docs.where(f"not _copy and _id is not null and octet_length(_text) >= {length}").select("_id", "_tie", "_text")

    pieces = fresh.mapInArrow(_anchor_pieces(bits, length), "block int, tokens binary, counts binary").groupBy("block")
    segments = stash(pieces.applyInArrow(_anchor_segments(bits, (2, HOT)), "block int, map0 binary, map1 binary"), "anchors")
    repeated, hot = _bitmaps(segments, bits, 2)
    hashes = fresh.mapInArrow(_surrounding_hashes(repeated, bits, length), "block int, tokens binary, hashes binary").groupBy("block")
    (mixed,) = _bitmaps(stash(hashes.applyInArrow(_mixed_segments(bits), "block int, map0 binary"), "mixed"), bits, 1)

    schema = "block int, kind byte, doc binary, tie binary, place binary, off binary, size binary, data binary"
    around = fresh.mapInArrow(_surroundings(repeated, hot, mixed, bits, length), schema)
    spans = around.groupBy("block").applyInArrow(_settle(length), "doc long, tie long, starts array<int>, ends array<int>")
    spans = stash(spans.groupBy("doc", "tie").agg(F.collect_list(F.struct("starts", "ends")).alias("_spans")), "spans")

    keys = maybe_broadcast(spans.select(F.col("doc").alias("_id"), F.col("tie").alias("_tie")), 32)
    live = docs.where("not _copy")
    touched = live.join(keys, ["_id", "_tie"], "left_semi").join(spans.select(F.col("doc").alias("_id"), F.col("tie").alias("_tie"), "_spans"), ["_id", "_tie"])
    cut = touched.select("_id", "_text", "_spans").mapInArrow(_cut_rows, "_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
    nothing = F.lit(0).cast("long")
    whole = F.octet_length("_text").cast("long")
    untouched = live.join(keys, ["_id", "_tie"], "left_anti").select("_id", whole.alias("n_bytes"), nothing.alias("n_removed"), nothing.alias("n_spans"), F.col("_sha").alias("kept_sha256"), F.col("_text").cast("binary").alias("kept"))
    copies = docs.where("_copy").select("_id", whole.alias("n_bytes"), whole.alias("n_removed"), F.lit(1).cast("long").alias("n_spans"), F.lit(EMPTY_SHA).alias("kept_sha256"), F.lit(b"").alias("kept"))
    return cut.union(untouched).union(copies).withColumnRenamed("_id", ident)
