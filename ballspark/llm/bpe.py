"""Token ids by the tokenizers library, each distinct pre-token merged once a process.

Byte-level BPE never merges across pre-tokens, so a text's ids are its pre-tokens' ids in a row. Whole
arrays of texts are split at once: a byte's class and its neighbours' say whether a pre-token begins
there, as long as all characters are ASCII or Latin letters. Other texts are split by the standard
``re`` module where every character has the same class there as in the tokenizer's pattern; all
other texts, and tokenizers of another make, go to the library whole. Pre-tokens are looked up by 128-bit
hashes of their bytes; the library's model merges those that aren't known, many in one call.
"""

from __future__ import annotations

import json
import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import batch_of, held, portions, text_or_empty

#: Pre-tokens kept in a process; the share of them that stays when there are as many; characters that are split at once.
CACHE, KEPT, TOGETHER = 1_200_000, 0.25, 600_000

SPLIT = re.compile(r"'(?:[stmd]|re|ve|ll)| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]+|_+)+|\s+(?!\S)|\s+")
#: Classes of bytes; END stands between texts.
END, BLANK, GAP, LETTER, DIGIT, MARK = range(6)
END_BYTE = 0xFF


def _known_characters() -> list[str]:
    """Those that are proved to be of one class in both pattern languages."""
    pairs = [(re.compile(r"[^\W\d_]"), regex.compile(r"\p{L}")), (re.compile(r"\d"), regex.compile(r"\p{N}")), (re.compile(r"\s"), regex.compile(r"\s"))]
    return [c for c in map(chr, [*range(0x250), *range(0x2010, 0x2028), 0x20AC]) if not "\x1c" <= c <= "\x1f" and all(bool(a.match(c)) == bool(b.match(c)) for a, b in pairs)]


def _byte_classes() -> np.ndarray:
    """Of ASCII by the patterns; bytes above are those of Latin letters."""
    out = np.full(256, LETTER, np.uint8)
    for b in range(128):
        c = chr(b)
        out[b] = BLANK if c == " " else GAP if c.isspace() else DIGIT if c.isdigit() else LETTER if c.isalpha() else MARK
    out[END_BYTE] = END
    return out


def _byte_alphabet() -> np.ndarray:
    """The character that byte-level vocabularies write for each byte: itself where it prints, else the next from U+0100 on."""
    prints = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    others = iter(range(0x100, 0x200))
    return np.array([b if b in prints else next(others) for b in range(256)], np.uint32)


CLASSES, ALPHABET = _byte_classes(), _byte_alphabet()


def starts(data: np.ndarray) -> np.ndarray:
    """Whether a pre-token starts at each byte of texts with END_BYTE between them and at least three of it behind."""
    c = CLASSES[data]
    before, after = np.zeros_like(c), np.zeros_like(c)
    before[1:], after[:-1] = c[:-1], c[1:]
    # of several white characters before a text goes on the last one is for itself, and a blank goes with what follows
    gap = (c == BLANK) | (c == GAP)
    out = np.where(gap, (before != BLANK) & (before != GAP) | (after > GAP), (c != before) & (before != BLANK) | (c == END))
    at = np.nonzero((data == ord("'")) & out)[0]
    one, two = data[at + 1], data[at + 2]
    short = np.isin(one, np.frombuffer(b"stmd", np.uint8))
    long = (two == ord("e")) & ((one == ord("r")) | (one == ord("v"))) | (one == ord("l")) & (two == ord("l"))
    out[at[short | long] + 1] = False
    out[at[short] + 2] = True
    out[at[long] + 3] = True
    return out


class Hashes:
    """Two 64-bit hashes of stretches of bytes: sums of a number for each byte times a power for its place."""

    def __init__(self):
        random = np.random.default_rng(20)
        self.numbers = random.integers(0, 1 << 64, (2, 256), np.uint64, endpoint=False)
        self.bases = [0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93]
        self.inverses = [pow(b, -1, 1 << 64) for b in self.bases]
        self.powers = [np.ones(1, np.uint64)] * 4

    def of(self, data: np.ndarray, begin: np.ndarray, end: np.ndarray) -> list[np.ndarray]:
        if len(self.powers[0]) < len(data):
            self.powers = [np.append(np.uint64(1), np.cumprod(np.full(len(data), b, np.uint64))) for b in (*self.bases, *self.inverses)]
        out = []
        for k in range(2):
            sums = np.zeros(len(data) + 1, np.uint64)
            np.cumsum(self.numbers[k][data] * self.powers[k][: len(data)], out=sums[1:])
            out.append((sums[end] - sums[begin]) * self.powers[2 + k][begin])
        return out


class Table:
    """Ids by hash: open addressing over arrays, and a pool of ids. Bounded; what is asked for least goes."""

    def __init__(self, dtype: np.dtype, most: int):
        self.most, self.dtype = most, dtype
        self.clear()

    def clear(self) -> None:
        self.n = 0
        self.hash, self.check = np.zeros(1024, np.uint64), np.zeros(1024, np.uint64)
        self.begin, self.size, self.uses = (np.zeros(1024, np.int32) for _ in range(3))
        self.pool, self.pooled = np.zeros(4096, self.dtype), 0
        self._slots(1 << 12)

    def _slots(self, n: int) -> None:
        self.shift = np.uint64(65 - n.bit_length())
        self.slot = np.full(n, -1, np.int32)
        self._place(np.arange(self.n))

    def _at(self, h: np.ndarray) -> np.ndarray:
        return (h * np.uint64(0xA0761D6478BD642F) >> self.shift).astype(np.int64)

    def _place(self, entries: np.ndarray) -> None:
        at = self._at(self.hash[entries])
        while len(entries):
            free = self.slot[at] < 0
            self.slot[at[free]] = entries[free]  # of several for one slot the last stays
            left = self.slot[at] != entries
            entries, at = entries[left], (at[left] + 1) & (len(self.slot) - 1)

    def find(self, h: np.ndarray, check: np.ndarray) -> np.ndarray:
        """The entry of each hash, -1 where there is none."""
        at = self._at(h)
        out = self.slot[at]
        open = np.nonzero((out >= 0) & ((self.hash[out] != h) | (self.check[out] != check)))[0]
        at = at[open]
        while len(open):
            at = (at + 1) & (len(self.slot) - 1)
            entry = self.slot[at]
            out[open] = entry
            on = (entry >= 0) & ((self.hash[entry] != h[open]) | (self.check[entry] != check[open]))
            open, at = open[on], at[on]
        return out

    def add(self, h: np.ndarray, check: np.ndarray, ids: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """New entries, of hashes that are not there; returns their numbers."""
        n = self.n + len(h)
        for name in ("hash", "check", "begin", "size", "uses"):
            if len(a := getattr(self, name)) < n:
                setattr(self, name, np.concatenate([a, np.zeros(max(n - len(a), len(a)), a.dtype)]))
        if len(self.pool) < self.pooled + len(ids):
            self.pool = np.concatenate([self.pool, np.zeros(max(len(ids), len(self.pool)), self.dtype)])
        new = np.arange(self.n, n)
        self.hash[new], self.check[new], self.size[new], self.uses[new] = h, check, sizes, 0
        self.begin[new] = self.pooled + np.cumsum(sizes) - sizes
        self.pool[self.pooled : self.pooled + len(ids)] = ids
        self.n, self.pooled = n, self.pooled + len(ids)
        if 2 * n > len(self.slot):
            self._slots(1 << (4 * n).bit_length() - 1)
        else:
            self._place(new)
        return new

    def ids(self, entries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The entries' ids in a row, and where each one's end."""
        sizes = self.size[entries]
        ends = np.cumsum(sizes, dtype=np.int64)
        return self.pool[np.repeat(self.begin[entries] - ends + sizes, sizes) + np.arange(ends[-1] if len(ends) else 0)], ends

    def age(self) -> None:
        """Once there are too many entries, those that were asked for least go."""
        if self.n <= self.most:
            return
        stay = np.sort(np.argpartition(-self.uses[: self.n], int(KEPT * self.most))[: int(KEPT * self.most)])
        (ids, _), kept = self.ids(stay), [a[stay] for a in (self.hash, self.check, self.size, self.uses)]
        self.clear()
        again = self.add(kept[0], kept[1], ids, kept[2])  # makes the arrays anew
        self.uses[again] = kept[3] // 2


class Encoder:
    """Ids of texts as bytes: unsigned little-endian, two bytes an id where the vocabulary allows it, else four."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, pre_tokenizers

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as file:
            made = json.load(file)
        pre = made.get("pre_tokenizer") or {}
        self.by_pieces = pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space") and not made.get("normalizer") and not made["model"].get("ignore_merges") and not made["model"].get("dropout")
        self.dtype = np.dtype("<u2" if self.library.get_vocab_size() <= 1 << 16 else "<u4")
        self.added = {t["content"]: t["id"] for t in made.get("added_tokens", [])}
        if any(t.get("lstrip") or t.get("rstrip") or t.get("single_word") or t.get("normalized") and not t.get("special") for t in made.get("added_tokens", [])):
            self.by_pieces = False
        self.at_added = re.compile("(" + "|".join(re.escape(k) for k in sorted(self.added, key=len, reverse=True)) + ")") if self.added else None
        known = _known_characters()
        self.other = re.compile(f"[^{re.escape(''.join(known))}]")
        self.not_plain = re.compile(f"[^{re.escape(''.join(c for c in known if c < '\x80' or c >= '\xc0' and c.isalpha()))}]")
        self.table, self.hashes = Table(self.dtype, CACHE), Hashes()
        #: The library's own model alone, for pre-tokens that are already in the alphabet of bytes, with blanks between them.
        self.merger = Tokenizer(self.library.model)
        self.merger.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        #: Bytes that each id stands for, where the tokenizer is byte-level: its strings have a character for each byte.
        vocabulary = self.library.get_vocab(with_added_tokens=True)
        self.lengths = np.zeros(max(vocabulary.values(), default=0) + 1, np.int64)
        self.lengths[list(vocabulary.values())] = [len(k) for k in vocabulary]

    def merge(self, data: np.ndarray, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, how many of each) of pre-tokens, all in one call; their ids part where their bytes do."""
        lengths = end - begin
        ends = np.cumsum(lengths)
        place = np.arange(ends[-1]) + np.repeat(np.arange(len(lengths)), lengths)
        written = np.full(ends[-1] + len(lengths), ord(" "), np.uint32)
        written[place] = ALPHABET[data[np.repeat(begin - ends + lengths, lengths) + np.arange(ends[-1])]]
        found = np.array(self.merger.encode_batch_fast([written.tobytes().decode("utf-32-le")], add_special_tokens=False)[0].ids, np.int64)
        stops = np.searchsorted(np.cumsum(self.lengths[found]), ends) + 1
        return found, np.diff(stops, prepend=0)

    def entries(self, data: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        """The table's entry of each pre-token; unknown ones are learned. Valid until the table ages."""
        h, check = self.hashes.of(data, begin, end)
        out = self.table.find(h, check)
        new = np.nonzero(out < 0)[0]
        if len(new):
            order = new[np.lexsort((check[new], h[new]))]
            first = np.ones(len(order), bool)
            first[1:] = (h[order][1:] != h[order][:-1]) | (check[order][1:] != check[order][:-1])
            one = order[first]
            entry = self.table.add(h[one], check[one], *self.merge(data, begin[one], end[one]))
            out[order] = entry[np.cumsum(first) - 1]
        np.add.at(self.table.uses, out, 1)
        return out

    def know(self, strings: list[bytes], ids: np.ndarray) -> None:
        """Enters strings that are known to be one token each, and no merging."""
        data = np.frombuffer(b"".join(strings), np.uint8)
        end = np.cumsum([len(s) for s in strings], dtype=np.int64)
        h, check = self.hashes.of(data, np.append(0, end)[:-1], end)
        new = np.nonzero(self.table.find(h, check) < 0)[0]
        self.table.add(h[new], check[new], ids[new], np.ones(len(new), np.int64))

    def split(self, texts: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """(bytes, begins, ends, which text) of the pre-tokens of texts, as many at once as TOGETHER allows; each text's in order.

        Of texts without added tokens and without characters that only the library splits.
        """
        plain = ([], [])
        odd = []
        size = 0

        def together() -> tuple[np.ndarray, ...]:
            stretches, of = plain
            data = np.frombuffer(b"\xff".join(stretches) + b"\xff" * 3, np.uint8)
            at = np.nonzero(starts(data))[0]
            end = np.append(at[1:], len(data))
            real = data[at] != END_BYTE
            which = np.cumsum(~real) - (~real)
            return data, at[real], end[real], np.array(of)[which[real]]

        for i, text in enumerate(texts):
            if self.not_plain.search(text):
                odd.append((i, text))
                continue
            for part in stretches_of(text, TOGETHER):
                plain[0].append(part.encode())
                plain[1].append(i)
                size += len(part)
                if size >= TOGETHER:
                    yield together()
                    plain[0].clear()
                    plain[1].clear()
                    size = 0
        if plain[0]:
            yield together()
        for i, text in odd:
            for part in stretches_of(text, TOGETHER):
                data = np.frombuffer(part.encode(), np.uint8)
                end = np.cumsum([len(p.encode()) for p in SPLIT.findall(part)], dtype=np.int64)
                yield data, np.append(0, end)[:-1], end, np.full(len(end), i)

    def whole(self, text: str) -> bool:
        """Whether the library has to take the text whole."""
        return not self.by_pieces or self.other.search(text) is not None

    def _bytes(self, ids: list[int]) -> bytes:
        return np.asarray(ids, self.dtype).tobytes()

    def encode(self, texts: list[str]) -> list[bytes]:
        out: list[bytes] = []
        for some in portions(texts, TOGETHER):
            out += self._encode(some)
        return out

    def _encode(self, texts: list[str]) -> list[bytes]:
        out, split = [b""] * len(texts), []
        for i, t in enumerate(texts):
            if self.whole(t):
                out[i] = self._bytes(self.library.encode(t, add_special_tokens=False).ids)
            elif self.at_added and any(k in t for k in self.added):
                parts = self.at_added.split(t)
                between = iter(self.encode(parts[::2]))
                out[i] = b"".join(self._bytes([self.added[p]]) if k % 2 else next(between) for k, p in enumerate(parts))
            elif t:
                split.append(i)
        for data, begin, end, which in self.split([texts[i] for i in split]):
            ids, ends = self.table.ids(self.entries(data, begin, end))
            cuts = np.nonzero(np.diff(which))[0]
            stops = [*ends[cuts].tolist(), len(ids)]
            raw, at, size = ids.tobytes(), 0, self.dtype.itemsize
            for i, stop in zip([*which[cuts].tolist(), int(which[-1])], stops):
                out[split[i]] += raw[at * size : stop * size]
                at = stop
            self.table.age()
        return out


def stretches_of(text: str, most: int) -> Iterator[str]:
    """The text in stretches of about ``most`` characters, each but the first with a pre-token's blank in front."""
    begin = 0
    while len(text) - begin > 2 * most:
        cut = AT_BLANK.search(text, begin + most)
        if cut is None:
            break
        yield text[begin : cut.start()]
        begin = cut.start()
    yield text[begin:] if begin else text


#: A blank before something else than white space always begins a pre-token.
AT_BLANK = re.compile(r" (?=\S)")


def encoder(path: str) -> Encoder:
    return held(("encoder", path), lambda: Encoder(path))


def token_ids(docs: DataFrame, path: str, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids, n): each whole text's ids and ``end_id`` after them; a null text is an empty one.

    ``ids`` are bytes, two or four an id as ``Encoder`` says. Texts of any length are encoded in stretches, repeated
    rows are rows of their own, and columns beside the two that are read play no part, whatever their names.
    """
    schema = pa.schema([("id", pa.int64()), ("ids", pa.binary()), ("n", pa.int64())])

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = encoder(path)
        end = e._bytes([end_id])
        for batch in batches:
            ids = [x + end for x in e.encode(batch.column(1).to_pylist())]
            yield batch_of(schema, {"id": batch.column(0), "ids": ids, "n": [len(x) // e.dtype.itemsize for x in ids]})

    return docs.select(docs[id_col].cast("long").alias("id"), text_or_empty(text_col)).mapInArrow(encode, "id long, ids binary, n long")


def id_type(path: str) -> np.dtype:
    return encoder(path).dtype
