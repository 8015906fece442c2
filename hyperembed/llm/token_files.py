"""Token ids in binary files of directly addressable codes.

A file holds a run of documents, in ascending order of id, as one sequence of ids. The sequence is cut into chunk levels:
level 0 has the lowest bits of every id, level 1 the next bits of those ids that need them, and so on. A bitmap per level
marks the ids that go on, and a rank directory counts them per 512, so any id is found with one probe per level and no
block is decoded. Chunk widths are the cheapest for the file's own distribution of id lengths.

Order of files is the order of the range partitions, so a document's start is known from the counts of the files before it.
Defined results: a null text counts as empty (its document has the end id alone); null ids come first; rows that repeat a
doc_id are documents of their own, ordered by a hash of the text; an empty table gives no file.
"""

from __future__ import annotations

import functools
import itertools
import json
import re
import struct
import uuid
import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window, functions as F

from .common import bounded_batches, new_folder, stash, without_cycles

MAGIC = b"DACIDS01"
#: Bits of the bitmap that one entry of the rank directory stands for.
RANK = 512
#: Chunk widths to choose from, in bits.
WIDTHS = (8, 16)
#: A file is closed after so many ids; a longer document has a file of its own.
FILE_IDS = 1_000_000
#: The usual runs of white space; texts with them are encoded whole, as are those with a word that `_is_odd`.
_INNER_BLANK = ("  ", "\n\n", " \n", "\n ")
#: A word of letters, then punctuation: the pre-tokeniser gives the letters with their space, then the punctuation.
_SIMPLE = re.compile(r"([\0\n]?)([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u017f]+)([!-/:-@\[-`{-~]{0,8})")


def _byte_letters() -> dict[int, str]:
    """Byte-level BPE writes each byte as one letter: printable Latin-1 as itself, the others from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    letter = {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(x for x in range(256) if x not in plain)}
    return {c: "".join(letter[b] for b in chr(c).encode()) for c in range(0x80, 0x180)}


_BYTE_LEVEL = _byte_letters()
_BIT_LENGTH = np.array([x.bit_length() for x in range(1 << 16)], np.uint8)
FILES_SCHEMA = "part int, seq int, path string, docs long, ids long"


def chunk_widths(lengths: np.ndarray) -> list[int]:
    """Widths (of WIDTHS, lowest first) with the fewest bits in all; lengths[k] is the number of ids of k bits."""
    top = max(1, int(np.flatnonzero(lengths).max()) if lengths.any() else 1)
    longer = lengths[::-1].cumsum()[::-1]  # ids of at least k bits
    best, bits = {0: (0.0, [])}, 0
    for bits in range(2, top + max(WIDTHS) + 2, 2):
        found = []
        for w in WIDTHS:
            if bits - w in best and bits - w < top:
                n = lengths.sum() if bits == w else (longer[bits - w + 1] if bits - w + 1 < len(longer) else 0)
                cost, widths = best[bits - w]
                found.append((cost + float(n) * (w + (1 + 32 / RANK if bits < top else 0)), [*widths, w]))
        if found:
            best[bits] = min(found)
    return min(v for k, v in best.items() if k >= top)[1]


def _pack(values: np.ndarray, width: int) -> bytes:
    if width >= 8:
        return values.astype(f"<u{width // 8}").tobytes()
    per = 8 // width
    v = np.zeros((len(values) + per - 1) // per * per, np.uint8)
    v[: len(values)] = values
    v = v.reshape(-1, per)
    out = np.zeros(len(v), np.uint8)
    for k in range(per):
        out |= v[:, k] << np.uint8(k * width)
    return out.tobytes()


def _unpack(data: bytes, width: int, n: int) -> np.ndarray:
    if width >= 8:
        return np.frombuffer(data, f"<u{width // 8}", n)
    raw = np.frombuffer(data, np.uint8)
    per = 8 // width
    out = np.empty((len(raw), per), np.uint8)
    for k in range(per):
        out[:, k] = (raw >> np.uint8(k * width)) & np.uint8((1 << width) - 1)
    return out.reshape(-1)[:n]


def encode_file(ids: np.ndarray, doc_ids: list, lengths: np.ndarray) -> bytes:
    """The bytes of a file: magic, header, document table, then chunks, bitmap and rank directory of each level."""
    v = ids.astype(np.uint32)
    if len(v) and v.max() < len(_BIT_LENGTH):
        lengths_of = np.bincount(_BIT_LENGTH[v], minlength=34)
    else:
        reach = np.array([np.count_nonzero(v >> np.uint32(k)) for k in range(32)] + [0, 0])  # ids of more than k bits
        lengths_of = np.r_[len(v) - reach[0], reach[:-1] - reach[1:]]
    widths = chunk_widths(lengths_of)
    parts, levels, at = [], [], 0

    def add(data: bytes) -> int:
        nonlocal at
        parts.append(data)
        at += len(data)
        return at - len(data)

    known = np.array([d is not None for d in doc_ids], bool)
    docs = {"ids": add(np.array([d or 0 for d in doc_ids], "<i8").tobytes()), "known": add(np.packbits(known, bitorder="little").tobytes()),
            "ends": add(np.cumsum(lengths, dtype=np.uint64).astype("<u8").tobytes()), "n": len(doc_ids)}
    for k, w in enumerate(widths):
        level = {"width": w, "n": len(v), "chunks": add(_pack(v & np.uint32((1 << w) - 1), w))}
        if k + 1 < len(widths):
            v = v >> np.uint32(w)
            on = v > 0
            level["bitmap"] = add(np.packbits(on, bitorder="little").tobytes())
            per = np.add.reduceat(on, np.arange(0, len(on), RANK), dtype=np.uint32) if len(on) else np.zeros(0, np.uint32)
            level["ranks"] = add((np.cumsum(per, dtype=np.uint32) - per).astype("<u4").tobytes())
            v = v[on]
        levels.append(level)
    head = json.dumps({"ids": len(ids), "docs": docs, "levels": levels}).encode()
    return MAGIC + struct.pack("<I", len(head)) + head + b"".join(parts)


class TokenFile:
    """Reader over a seekable file (or bytes): single ids by probes, documents and whole files by vectors."""

    def __init__(self, source):
        self.f = pa.BufferReader(source) if isinstance(source, bytes) else source
        if self._read(0, 8) != MAGIC:
            raise ValueError("not a token file")
        (n,) = struct.unpack("<I", self._read(8, 4))
        self.head = json.loads(self._read(12, n))
        self.base, self.levels, self.docs = 12 + n, self.head["levels"], self.head["docs"]

    def _read(self, at: int, n: int) -> bytes:
        self.f.seek(at)
        return self.f.read(n)

    def _at(self, offset: int, n: int) -> bytes:
        return self._read(self.base + offset, n)

    def __len__(self) -> int:
        return self.head["ids"]

    def __getitem__(self, i: int) -> int:
        """One id: per level one chunk, one bitmap block and one directory entry are read."""
        if not 0 <= i < len(self):
            raise IndexError(i)
        value, shift = 0, 0
        for level in self.levels:
            w = level["width"]
            first = i * w // 8
            chunk = int.from_bytes(self._at(level["chunks"] + first, max(1, w // 8)), "little") >> (i * w % 8 if w < 8 else 0)
            value |= (chunk & ((1 << w) - 1)) << shift
            shift += w
            if "bitmap" not in level:
                break
            block = i // RANK
            bits = int.from_bytes(self._at(level["bitmap"] + block * RANK // 8, min(RANK, level["n"] - block * RANK + 7) // 8 + 1), "little")
            here = i - block * RANK
            if not bits >> here & 1:
                break
            before = int.from_bytes(self._at(level["ranks"] + 4 * block, 4), "little")
            i = before + (bits & ((1 << here) - 1)).bit_count()
        return value

    def all_ids(self) -> np.ndarray:
        value, shift, at = np.zeros(len(self), np.uint32), 0, None
        for level in self.levels:
            w, n = level["width"], level["n"]
            chunk = _unpack(self._at(level["chunks"], (n * w + 7) // 8), w, n).astype(np.uint32) << np.uint32(shift)
            if at is None:
                value |= chunk
            else:
                value[at] |= chunk
            shift += w
            if "bitmap" not in level:
                break
            on = np.flatnonzero(np.unpackbits(np.frombuffer(self._at(level["bitmap"], (n + 7) // 8), np.uint8), count=n, bitorder="little"))
            at = on if at is None else at[on]
        return value

    def documents(self) -> tuple[list, np.ndarray]:
        """(ids of documents, end of each in the file's sequence)."""
        n = self.docs["n"]
        ids = np.frombuffer(self._at(self.docs["ids"], 8 * n), "<i8").tolist()
        known = np.unpackbits(np.frombuffer(self._at(self.docs["known"], (n + 7) // 8), np.uint8), count=n, bitorder="little")
        return [d if k else None for d, k in zip(ids, known)], np.frombuffer(self._at(self.docs["ends"], 8 * n), "<u8").astype(np.int64)


class CachedEncoder:
    """Byte-level BPE ids of texts by the tokenizers library, with a cache of space-led words.

    The pre-tokeniser starts a new piece at every space before a character that is not white space, so such words encode
    alike alone and in their text; texts where a space precedes white space, or with a special token's string, go whole.
    Odd words are never kept, so that each text with one is seen.
    """

    def __init__(self, vocabulary: str, entries: int = 260_000):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(vocabulary)
        self.model, self.tails = self.tokenizer.model, {}
        (self.line_feed,) = self._encode(["\n"])
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.new: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.entries = entries

    def _piece(self, piece: str) -> bytes:
        """Ids of one piece of the pre-tokeniser, already in its byte-level letters."""
        return array("I", [t.id for t in self.model.tokenize(piece)]).tobytes()

    def _encode(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, missing: set[str]) -> set[str]:
        """Put words into the cache, but for the odd ones, which are returned."""
        new, old, tokenize, other = self.new, self.old, self.model.tokenize, []
        for w in missing:
            ids = old.get(w)
            if ids is None:
                if w.isascii() and w.isalpha():
                    ids = array("I", [t.id for t in tokenize(f"\u0120{w}")]).tobytes()
                elif m := _SIMPLE.fullmatch(w):
                    lead, stem, tail = m.groups()
                    head = f"{lead}{stem}"
                    ids = (new.get(head) or old.get(head)) if tail else None
                    if ids is None:
                        letters = stem if stem.isascii() else stem.translate(_BYTE_LEVEL)
                        ids = self._piece(f"\u0120{letters}") if not lead else self._piece(letters) if lead == "\0" else self.line_feed + self._piece(letters)
                        new[head] = ids
                    if tail:
                        end = self.tails.get(tail)
                        if end is None:
                            end = self.tails[tail] = self._piece(tail)
                        ids = ids + end
                else:
                    other.append(w)
                    continue
            new[w] = ids
        odd = {w for w in other if _is_odd(w)}
        other = [w for w in other if w not in odd]
        for i in range(0, len(other), 4096):
            part = other[i: i + 4096]
            new.update(zip(part, self._encode([w[1:] if w[:1] == "\0" else w if w[:1] == "\n" else f" {w}" for w in part])))
        return odd

    def encode(self, texts: list[str]) -> list[bytes]:
        """For each text its ids as little-endian unsigned 32-bit integers.

        Keys of the cache: words without the space before them; words after a line feed with it; a text's first word after a NUL.
        """
        new, split, missing = self.new, [], set()
        for text in texts:
            if any([x in text for x in _INNER_BLANK]) or "\0" in text or any([x in text for x in self.special]):
                split.append(None)
                continue
            words = f"\0{text}".replace("\n", " \n").split(" ")
            ids = list(map(new.get, words))
            gaps = []
            if None in ids:
                gaps = [i for i, x in enumerate(ids) if x is None]
                missing.update([words[i] for i in gaps])
            split.append((words, ids, gaps))
        odd = self._learn(missing) if missing else None
        out, whole = [b""] * len(texts), []
        for k, entry in enumerate(split):
            if entry is None:
                whole.append(k)
                continue
            words, ids, gaps = entry
            if odd and not odd.isdisjoint([words[i] for i in gaps]):
                whole.append(k)
                continue
            for i in gaps:
                ids[i] = new[words[i]]
            out[k] = b"".join(ids)
        for k, ids in zip(whole, self._encode([texts[k] for k in whole])):
            out[k] = ids
        if len(new) > self.entries:
            self.old, self.new = new, {}
        return out


def _is_odd(word: str) -> bool:
    """Whether a key stands for a run of white space: nothing behind its space or line feed, or white space at either end."""
    core = word[1:] if word[:1] in ("\0", "\n") else word
    return core[:1].isspace() or core[-1:].isspace() if core else word != "\0"


@functools.cache
def worker_encoder(vocabulary: str) -> CachedEncoder:
    """One encoder for all tasks of a Python worker."""
    return CachedEncoder(vocabulary)


def _file_writer(folder: str, vocabulary: str, end_id: int):
    def run(batches):
        fs, base = pafs.FileSystem.from_uri(folder)
        encoder, end = worker_encoder(vocabulary), struct.pack("<I", end_id)
        part, seq, docs, ids, n = TaskContext.get().partitionId(), 0, [], [], 0

        def flush():
            path = f"{base}/{uuid.uuid4().hex}.dac"
            lengths = np.array([len(x) // 4 for x in ids], np.int64)
            with fs.open_output_stream(path, compression=None) as out:
                out.write(encode_file(np.frombuffer(b"".join(ids), "<u4"), docs, lengths))
            return pa.RecordBatch.from_pylist([{"part": part, "seq": seq, "path": path, "docs": len(docs), "ids": int(lengths.sum())}],
                                              pa.schema([("part", pa.int32()), ("seq", pa.int32()), ("path", pa.string()), ("docs", pa.int64()), ("ids", pa.int64())]))

        for b in batches:
            for at in range(0, b.num_rows, 512):
                rows = b.slice(at, 512)
                with without_cycles():
                    found = encoder.encode([t or "" for t in rows.column(1).to_pylist()])
                for d, x in zip(rows.column(0).to_pylist(), found):
                    docs.append(d)
                    ids.append(x + end)
                    n += len(x) // 4 + 1
                    if n >= FILE_IDS:
                        yield flush()
                        seq, docs, ids, n = seq + 1, [], [], 0
        if docs:
            yield flush()

    return run


def write_token_files(df: DataFrame, folder: str, vocabulary: str, end_id: int = 2, text: str = "text", ident: str = "doc_id", parts: int | None = None) -> DataFrame:
    """Encode every text, append `end_id`, write files in ascending order of id; returns (part, seq, path, docs, ids, start)."""
    fs, base = pafs.FileSystem.from_uri(folder)
    fs.create_dir(base, recursive=True)
    spark = df.sparkSession
    bounded_batches(spark)
    docs = df.select(F.col(ident).cast("long").alias("_id"), F.col(text).alias("_text"), F.xxhash64(text).alias("_tie"))
    order = [F.col("_id").asc_nulls_first(), F.col("_tie")]
    docs = docs.repartitionByRange(parts or int(spark.conf.get("spark.sql.shuffle.partitions")), *order).sortWithinPartitions(*order)
    files = stash(docs.drop("_tie").mapInArrow(_file_writer(folder, vocabulary, end_id), FILES_SCHEMA), "token-files")
    # A row per file: two sums, over partitions and within one, so that no window holds all files.
    sizes = files.groupBy("part").agg(F.sum("ids").alias("_ids"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.select("part", F.coalesce(F.sum("_ids").over(before), F.lit(0)).alias("_before"))
    inside = Window.partitionBy("part").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    return files.join(sizes, "part").withColumn("start", F.col("_before") + F.coalesce(F.sum("ids").over(inside), F.lit(0))).drop("_before")


def _file_reader(folder: str, digest: bool):
    def run(batches):
        fs, _ = pafs.FileSystem.from_uri(folder)
        for b in batches:
            for path, start in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                with fs.open_input_file(path) as f:
                    file = TokenFile(f)
                    ids, (docs, ends) = file.all_ids().astype("<u4"), file.documents()
                starts = np.r_[0, ends[:-1]] if len(ends) else ends
                data = memoryview(ids).cast("B")
                if digest:
                    crc = [zlib.crc32(data[4 * s: 4 * e]) for s, e in zip(starts.tolist(), ends.tolist())]
                    yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(starts + start, pa.int64()), pa.array(ends - starts, pa.int64()), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])
                    continue
                for at in range(0, len(docs), 256):
                    k = slice(at, at + 256)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(docs[k], pa.int64()), pa.array(starts[k] + start, pa.int64()), pa.array([bytes(data[4 * s: 4 * e]) for s, e in zip(starts[k], ends[k])], pa.binary())],
                        ["doc_id", "start", "ids"],
                    )

    return run


def read_token_files(files: DataFrame, folder: str, digest: bool = False) -> DataFrame:
    """(doc_id, start, ids) of every document, ids as little-endian unsigned 32-bit integers; with `digest` (doc_id, start, n_tokens, ids_crc32)."""
    parts = int(files.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    spread = files.select("path", "start").repartition(max(1, min(files.count(), parts)))
    return spread.mapInArrow(_file_reader(folder, digest), "doc_id long, start long, n_tokens long, ids_crc32 long" if digest else "doc_id long, start long, ids binary")


def unpack_ids(column):
    """Array of ids of the `ids` column, in Spark functions."""
    hexed = F.hex(column)
    return F.transform(
        F.sequence(F.lit(0), (F.octet_length(column) / 4 - 1).cast("int")),
        lambda i: F.conv(F.concat(*[F.substring(hexed, i * 8 + k, 2) for k in (7, 5, 3, 1)]), 16, 10).cast("long"),
    )


def tokens_round_trip(df: DataFrame, vocabulary: str, digest: bool = False, **options) -> DataFrame:
    """Write the table's token files, then read every document back as `read_token_files` does."""
    folder = new_folder(df.sparkSession, "tokens")
    files = stash(write_token_files(df, folder, vocabulary, **options), "token-index")
    return read_token_files(files, folder, digest)


def random_access(file: TokenFile, places) -> list[int]:
    return [file[i] for i in itertools.islice(places, len(places))]
