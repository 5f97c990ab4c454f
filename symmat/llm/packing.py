"""Packing token sequences by best-fit decreasing over a segment tree of remaining capacities.

Documents are tokenised whole and cut into full windows; each full window is a sequence of its own. The remainders are
dealt at random over packing groups of bounded size; a group is packed in one task: pieces by falling length, each into
the open window of least sufficient room, which a segment tree indexed by room finds in O(log window). Padding that
dealing into groups adds is at most about one window a group.

Tokenising works on whole blocks of text: the units that the tokenizer cuts texts into are found on byte arrays, each
distinct unit of a block is merged once, and all of them side by side. Words it can't cut that way go through the
tokenizer library, as does every text if the vocabulary file is of another kind.
"""

from __future__ import annotations

import json
from array import array
from collections.abc import Iterator
from zlib import crc32

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import WordHasher, chunks, cut, parts_for, utf8, word_spans

WINDOW = 4096
END = 2
#: Remainders of one packing group on average.
PIECES_PER_GROUP = 50_000
#: Bytes of text whose units are merged together; a longer text is cut between words.
BLOCK = 2 << 20
#: Units of more bytes go through the tokenizer library.
LONGEST = 64
#: What the vocabulary file must say for units to be found here. Letters, single digits, endings behind an apostrophe, other marks.
NORMAL = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]
UNITS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
ENDINGS = ("s", "t", "re", "ve", "m", "ll", "d")

_LETTER, _DIGIT, _MARK, _ODD = 1, 2, 3, 4
_CLASS = np.full(256, _ODD, np.uint8)
_CLASS[:128] = _MARK
_CLASS[0x1C:0x20] = _ODD  # separators to some, marks to others: the library decides
_CLASS[[0x20, *range(0x09, 0x0E)]] = 0
_CLASS[0x30:0x3A] = _DIGIT
_CLASS[0x41:0x5B] = _CLASS[0x61:0x7B] = _LETTER
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 0x20
_WIDE = np.uint64(0x94D049BB133111EB)


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def latin_units(flat: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Lower-case bytes; start, end and oddness of every unit; and the first unit of each text (n+1 values).

    Words of ASCII and of the Latin letters that start with byte C3 are cut into units; any other word is one odd unit.
    """
    n = len(flat)
    lower, kind = _LOWER[flat], _CLASS[flat]
    lead = np.flatnonzero(flat == 0xC3)
    second = flat[lead + 1]
    letter = (second != 0x97) & (second != 0xB7)  # the signs of multiplication and division
    kind[lead[letter]] = kind[lead[letter] + 1] = _LETTER
    capital = lead[letter & (second < 0x9F)] + 1
    lower[capital] += 0x20
    start, end, first = word_spans(flat, offsets)
    opens = np.zeros(n + 1, bool)
    opens[1:n] = (kind[1:] != kind[:-1]) | (kind[1:] == _DIGIT)
    opens[:n] &= kind > 0
    opens[start] = True
    odd = np.zeros(len(start), bool)
    strange = kind == _ODD
    strange[:-1] |= (flat[:-1] == 0x3C) & (flat[1:] == 0x7C)  # perhaps a special token
    odd[np.searchsorted(start, np.flatnonzero(strange), side="right") - 1] = True
    marks = np.flatnonzero((flat == 0x27) & opens[:n])
    if len(marks):
        stop = end[np.searchsorted(start, marks, side="right") - 1]
        padded = np.append(lower, [0, 0])
        a, b = padded[marks + 1], padded[marks + 2]
        for ending in ENDINGS:
            k = len(ending)
            hit = (marks + k < stop) & (a == ord(ending[0])) & ((b == ord(ending[1])) if k == 2 else True)
            opens[marks[hit] + 1] = False
            after = marks[hit] + 1 + k
            after = after[after < stop[hit]]
            opens[after[kind[after] == _LETTER]] = True
    at = np.flatnonzero(opens[:n])
    word = np.searchsorted(start, at, side="right") - 1
    if odd.any():
        keep = ~odd[word] | (at == start[word])
        at, word = at[keep], word[keep]
    stop = end[word]
    if len(at):
        np.minimum(stop[:-1], at[1:], out=stop[:-1])
    return lower, at, stop, odd[word], np.searchsorted(at, offsets)


class Merges:
    """Byte-pair merging of many units at once: in each step, every unit merges its leftmost pair of lowest rank."""

    def __init__(self, vocab: dict[str, int], merges: list, suffix: str) -> None:
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves
        others = [b for b in range(256) if b not in plain]
        shown = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(others)}
        self.inner = np.array([vocab[shown[b]] for b in range(256)], np.int32)
        self.final = np.array([vocab[shown[b] + suffix] for b in range(256)], np.int32)
        pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
        self.result = np.array([vocab[a + b] for a, b in pairs], np.int32)
        self.none = len(pairs)
        self.bits = max(10, (8 * len(pairs)).bit_length())
        self.key = np.full(1 << self.bits, -1, np.int64)
        self.rank = np.full(1 << self.bits, self.none, np.int32)
        keys = np.array([vocab[a] << 32 | vocab[b] for a, b in pairs], np.int64)
        for k, slot, r in zip(keys.tolist(), self._slot(keys).tolist(), range(self.none)):
            while self.key[slot] >= 0:
                slot = (slot + 1) & ((1 << self.bits) - 1)
            self.key[slot], self.rank[slot] = k, r

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.view(np.uint64) * _WIDE) >> np.uint64(64 - self.bits)).astype(np.int64)

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair; ``none`` for pairs that don't merge."""
        key = left.astype(np.int64) << 32 | right
        slot = self._slot(key)
        seen, out = self.key[slot], self.rank[slot]  # an empty slot has rank ``none``
        open_ = np.flatnonzero((seen != key) & (seen >= 0))
        while len(open_):
            slot[open_] = (slot[open_] + 1) & ((1 << self.bits) - 1)
            seen = self.key[slot[open_]]
            out[open_] = self.rank[slot[open_]]
            open_ = open_[(seen != key[open_]) & (seen >= 0)]
        return out

    def of(self, flat: np.ndarray, start: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of units laid end to end, and the number of each unit's ids. Units are put through in groups of like length."""
        count = np.ones(len(start), np.int64)
        parts: list[tuple[np.ndarray, np.ndarray]] = []
        low = 0
        for high in (1, 4, 6, 8, 10, 12, 16, 24, 40, LONGEST):
            group = np.flatnonzero((length > low) & (length <= high))
            for s in range(0, len(group), 1 << 14):
                some = group[s : s + (1 << 14)]
                ids, count[some] = self._group(flat, start[some], length[some], high)
                parts.append((some, ids))
            low = high
        first = np.cumsum(count) - count
        out = np.empty(int(count.sum()), np.int32)
        for some, ids in parts:
            own = count[some]
            out[np.repeat(first[some] - (np.cumsum(own) - own), own) + np.arange(len(ids))] = ids
        return out, count

    def _group(self, flat: np.ndarray, start: np.ndarray, length: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        n = len(start)
        place = np.arange(width)
        raw = flat[start[:, None] + np.minimum(place, length[:, None] - 1)]
        s = np.where(place == length[:, None] - 1, self.final[raw], self.inner[raw])
        live = place < length[:, None]
        if width == 1:
            return s.ravel(), np.ones(n, np.int64)
        rank = np.full((n, width), self.none, np.int32)
        rank[:, :-1] = self.ranks(s[:, :-1].ravel(), s[:, 1:].ravel()).reshape(n, -1)
        rank[~live] = self.none
        rank[np.arange(n), length - 1] = self.none
        after = np.broadcast_to((place + 1).astype(np.int32), (n, width)).copy()
        before = np.broadcast_to((place - 1).astype(np.int32), (n, width)).copy()
        s, rank, after, before, live = s.ravel(), rank.ravel(), after.ravel(), before.ravel(), live.ravel()
        rows = np.arange(n)
        while len(rows):
            own = rank.reshape(n, width)[rows] if len(rows) < n else rank.reshape(n, width)
            p = own.argmin(axis=1)
            best = own[np.arange(len(rows)), p]
            go = best < self.none
            rows, p, best = rows[go], p[go], best[go]
            base = rows * width
            at = base + p
            gone = base + after[at]
            new = self.result[best]
            s[at], live[gone], rank[gone], rank[at] = new, False, self.none, self.none
            then = after[gone]
            after[at] = then
            has = then < length[rows]
            nxt = base[has] + then[has]
            before[nxt] = p[has]
            rank[at[has]] = self.ranks(new[has], s[nxt])
            prior = before[at]
            has = prior >= 0
            was = base[has] + prior[has]
            rank[was] = self.ranks(s[was], new[has])
        return s[live], live.reshape(n, width).sum(axis=1)


class WordIds:
    """Ids of texts, as little-endian 32-bit numbers, equal to the tokenizer library's."""

    def __init__(self, path: str) -> None:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.merges = self._known(spec)
        self.hasher = WordHasher(fold_ascii_case=False)

    @staticmethod
    def _known(spec: dict) -> Merges | None:
        """The merges, if the file's units are the ones found here; else None."""
        model, cutter = spec["model"], spec.get("pre_tokenizer") or {}
        parts = cutter.get("pretokenizers", [])
        usual = (
            (spec.get("normalizer") or {}).get("normalizers") == NORMAL
            and [p["type"] for p in parts] == ["Split", "ByteLevel"]
            and (parts[0]["pattern"], parts[0]["invert"], parts[0]["behavior"]) == ({"Regex": UNITS}, True, "Removed")
            and not parts[1]["add_prefix_space"] and not parts[1]["use_regex"]
            and model["type"] == "BPE" and not model.get("dropout") and not model.get("continuing_subword_prefix") and not model.get("ignore_merges")
            and all(t["content"].startswith("<|") for t in spec.get("added_tokens", []))
        )
        try:
            return Merges(model["vocab"], model["merges"], model.get("end_of_word_suffix") or "") if usual else None
        except KeyError:
            return None

    def block(self, flat: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of a block of texts end to end, and n+1 offsets."""
        if self.merges is None:
            texts = [flat[a:b].tobytes().decode("utf-8") for a, b in zip(offsets[:-1], offsets[1:])]
            found = [np.array(e.ids, "<u4") for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
            return np.concatenate([*found, np.zeros(0, "<u4")]), np.concatenate([[0], np.cumsum([len(x) for x in found])]).astype(np.int64)
        lower, start, end, odd, first = latin_units(flat, offsets)
        if not len(start):
            return np.zeros(0, "<u4"), np.zeros(len(offsets), np.int64)
        h = self.hasher.of(self.hasher.prefix(lower), start, end)
        if odd.any():
            h[odd] = self.hasher.of(self.hasher.prefix(flat), start[odd], end[odd]) ^ _WIDE
        code = pa.array(h).dictionary_encode().indices.to_numpy().astype(np.int64)
        top = np.maximum.accumulate(code)
        once = np.flatnonzero(np.diff(top, prepend=-1))  # codes are given in order of first sight
        s, size = start[once], end[once] - start[once]
        other = odd[once] | (size > LONGEST)
        count = np.empty(len(once), np.int64)
        ids, count[~other] = self.merges.of(lower, s[~other], size[~other])
        begin = np.empty(len(once), np.int64)
        begin[~other] = np.cumsum(count[~other]) - count[~other]
        if other.any():
            words = [flat[a : a + k].tobytes().decode("utf-8") for a, k in zip(s[other].tolist(), size[other].tolist())]
            found = [array("I", e.ids) for e in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]
            count[other] = [len(x) for x in found]
            begin[other] = len(ids) + np.cumsum(count[other]) - count[other]
            ids = np.concatenate([ids, *(np.frombuffer(x, np.uint32).astype(np.int32) for x in found if len(x))])
        per = count[code]
        to = np.concatenate([[0], np.cumsum(per)])
        out = ids[np.repeat(begin[code] - to[:-1], per) + np.arange(to[-1])]
        return out.astype("<u4"), to[first]

    def texts(self, column: pa.Array) -> Iterator[tuple[int, np.ndarray]]:
        """(position, ids) of every text; null counts as empty. A text longer than a block is cut between words."""
        flat, offsets = utf8(column)
        for i, j in chunks(offsets, BLOCK):
            part, at = flat[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
            if j == i + 1 and len(part) > 2 * BLOCK:
                yield i, np.concatenate([self.block(part[a:b], np.array([0, b - a]))[0] for a, b in _cuts(part)])
                continue
            ids, to = self.block(part, at)
            for k in range(j - i):
                yield i + k, ids[to[k] : to[k + 1]]


def _cuts(flat: np.ndarray) -> list[tuple[int, int]]:
    """Spans of about ``BLOCK`` bytes that end at blanks."""
    blank = np.flatnonzero(_CLASS[flat] == 0)
    edges = [0]
    while edges[-1] < len(flat):
        k = np.searchsorted(blank, edges[-1] + BLOCK)
        edges.append(int(blank[k]) + 1 if k < len(blank) else len(flat))
    return list(zip(edges[:-1], edges[1:]))


def _pieces(path: str, window: int, end: int):
    tail = np.array([end], "<u4")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = WordIds(path)
        for batch in batches:
            own, start, length, crc, total = [], [], [], [], []
            for k, ids in words.texts(batch.column("text")):
                ids = np.concatenate([ids, tail])
                for at in range(0, len(ids), window):
                    piece = ids[at : at + window]
                    own.append(k)
                    start.append(at)
                    length.append(len(piece))
                    crc.append(crc32(piece))
                    total.append(len(ids))
            doc = batch.column("doc_id").take(pa.array(own, pa.int64()))
            yield pa.RecordBatch.from_arrays([doc, *(pa.array(c, pa.int64()) for c in (start, length, crc, total))], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return run


def tokenise(docs: DataFrame, path: str | None = None, window: int = WINDOW, end: int = END) -> DataFrame:
    """Pieces of at most ``window`` ids: doc_id, start, length, ids_crc32, doc_tokens."""
    slim = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    names = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"
    return slim.mapInArrow(_pieces(path or vocabulary(), window, end), names)


def best_fit(lengths: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Window number and offset of each length (1..window), packed by best-fit decreasing; equal lengths in the order given."""
    size = 1 << window.bit_length()
    most = [0] * (2 * size)  # a tree over rooms 0..window: is a window of such room open below this node
    bins: list[list[int]] = [[] for _ in range(window + 1)]

    def mark(room: int, by: int) -> None:
        x = size + room
        while x:
            most[x] += by
            x >>= 1

    def tightest(room: int) -> int:
        """The least open room of at least ``room``, -1 if there is none."""
        x = size + room
        if most[x]:
            return room
        while x > 1:
            if not x & 1 and most[x + 1]:
                x += 1
                while x < size:
                    x = 2 * x if most[2 * x] else 2 * x + 1
                return x - size
            x >>= 1
        return -1

    number, offset = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    opened = 0
    for i in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[i])
        room = tightest(n)
        if room < 0:
            room, b, opened = window, opened, opened + 1
        else:
            b = bins[room].pop()
            mark(room, -1)
        number[i], offset[i] = b, window - room
        if room - n:
            bins[room - n].append(b)
            mark(room - n, 1)
    return number, offset


def pack(docs: DataFrame, path: str | None = None, window: int = WINDOW, end: int = END) -> DataFrame:
    """A row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A null or empty text is the end id alone. Rows that repeat a doc_id, or have none, are packed each. An empty table
    gives no rows. Sequence ids are unique; those of full windows are odd.
    """
    # numbers of the checkpointed rows deal equal documents over all groups
    pieces = cut(tokenise(docs, path, window, end)).withColumn("at", F.monotonically_increasing_id())
    rest = pieces.where(F.col("length") < window)
    groups = parts_for(rest.count(), PIECES_PER_GROUP)
    rest = rest.withColumn("g", F.pmod(F.xxhash64("at"), F.lit(groups)))

    def place(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["length", "at"], ascending=[False, True])
        number, offset = best_fit(pdf["length"].to_numpy(), window)
        return pdf.drop(columns=["g", "at"]).assign(sequence_id=(pdf["g"].to_numpy() << 33) + 2 * number, offset=offset)

    schema = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    packed = rest.select("doc_id", "at", "start", "length", "ids_crc32", "doc_tokens", "g").groupBy("g").applyInPandas(place, schema)
    numbered = pieces.where(F.col("length") == window).withColumn("sequence_id", 2 * F.col("at") + 1)
    return packed.unionByName(numbered.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", F.lit(0).cast("long").alias("offset")))
