"""Byte-level BPE encoding and decoding with a priority queue of merge ranks over a doubly linked symbol list."""

from __future__ import annotations

import hashlib
import heapq
import json
import re
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import slices, tidy

#: The pre-tokenizer's white space (Unicode White_Space) and its pattern.
_SPACE = r"\t-\r\x20\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
PIECES = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_SPACE}\p{{L}}\p{{N}}]+|[{_SPACE}]+(?![^{_SPACE}])|[{_SPACE}]+"
#: The same pattern for texts of ASCII only.
ASCII_PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?[A-Za-z]+| ?[0-9]+| ?[^\t-\r\x20A-Za-z0-9]+|[\t-\r\x20]+(?![^\t-\r\x20])|[\t-\r\x20]+"
_CACHE_ROWS = 150_000
_CACHE_PIECE = 64
_TOKENIZERS: dict[str, "ByteBpe"] = {}
_NEWER: dict[str, dict[str, str]] = {}


def _byte_letters() -> dict[str, int]:
    """The printable stand-ins of the 256 bytes: visible Latin-1 characters stand for themselves, the others follow from U+0100."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class Pieces:
    """Cuts texts into the pre-tokenizer's pieces, with the letters and numbers that the library knows.

    Its Unicode tables may be older than those of ``regex``; characters that they class otherwise are found by probing its
    pre-tokenizer with each letter and number once. Only texts with one of them take the slower exact pattern.
    """

    def __init__(self, newer: dict[str, str]):
        exact = PIECES
        for kind, letters in newer.items():
            if letters:
                exact = exact.replace(rf"\p{{{kind}}}", rf"[\p{{{kind}}}--[{letters}]]")
        every = "".join(newer.values())
        self.newer = frozenset(every)
        self.far = re.compile(f"[{min(every, default=chr(0x10FFFF))}-\U0010ffff]")
        near = [chr(c) for c in range(128, 0x250)]
        letters, numbers = ("".join(c for c in near if unicodedata.category(c)[0] == k) for k in "LN")
        latin = ASCII_PIECES.replace("A-Za-z", "A-Za-z" + letters).replace("0-9", "0-9" + numbers).replace(r"\t-\r\x20", r"\t-\r\x20\x85\xa0")
        self.latin, self.beyond = re.compile(latin), re.compile("[\u0250-\U0010ffff]")
        self.ascii, self.usual, self.exact = re.compile(ASCII_PIECES, re.ASCII), regex.compile(PIECES), regex.compile("(?V1)" + exact)

    def cut(self, text: str) -> list[str]:
        if text.isascii():
            return self.ascii.findall(text)
        if not self.beyond.search(text):
            return self.latin.findall(text)
        return (self.exact if self.far.search(text) and not self.newer.isdisjoint(text) else self.usual).findall(text)


def newer_of(path: str) -> dict[str, str]:
    """Letters (L) and numbers (N) that ``regex`` knows and the pre-tokenizer of the file does not. Asked once, on the driver, and sent along."""
    if path not in _NEWER:
        from tokenizers import Tokenizer

        cut = Tokenizer.from_file(path).pre_tokenizer.pre_tokenize_str
        text = "".join(map(chr, [*range(128, 0xD800), *range(0xE000, 0x110000)]))
        _NEWER[path] = {kind: "".join(c for c in regex.findall(rf"\p{{{kind}}}", text) if len(cut(lead + c)) > 1) for kind, lead in (("L", "a"), ("N", "1"))}
    return _NEWER[path]


class ByteBpe:
    """Encoder and decoder of a byte-level BPE file of the ``tokenizers`` library.

    Added tokens are found in the text first, as the library does by default. Texts may be null (encoded as
    empty) or of any length; work is linear in the text but for single pieces, which take n log n.
    """

    def __init__(self, path: str, newer: dict[str, str] | None = None):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        if (kind := spec["pre_tokenizer"]["type"]) != "ByteLevel" or spec.get("normalizer"):
            raise ValueError(f"not a plain byte-level file: {kind}")
        letters = _byte_letters()
        raw = lambda s: bytes(letters[c] for c in s)
        vocab = spec["model"]["vocab"]
        self.strings: dict[int, bytes] = {i: raw(s) for s, i in vocab.items()}
        self.single = [vocab[c] for c, _ in sorted(letters.items(), key=lambda x: x[1])]
        # left id and right id in one number -> rank and made id in one number: half the memory of tuples
        self.merges: dict[int, int] = {}
        for rank, pair in enumerate(spec["model"]["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            self.merges.setdefault(vocab[a] << 32 | vocab[b], rank << 32 | vocab[a + b])
        added = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.added = {s: np.uint32(i).tobytes() for s, i in added.items()}
        self.strings |= {i: s.encode() for s, i in added.items()}
        self.split = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(added, key=len, reverse=True)) + ")") if added else None
        self.pieces = Pieces(newer_of(path) if newer is None else newer)
        self.cache: dict[str, bytes] = {}

    def merge(self, data: bytes) -> list[int]:
        """Ids of one piece: the lowest rank merges first, the leftmost of equal ranks; entries that a merge made stale are skipped."""
        n = len(data)
        ids = [self.single[b] for b in data]
        if n < 2:
            return ids
        merges = self.merges
        after = list(range(1, n + 1))
        before = list(range(-1, n - 1))
        queue = []
        for i in range(n - 1):
            if (found := merges.get(ids[i] << 32 | ids[i + 1])) is not None:
                queue.append((found >> 32, i, ids[i], ids[i + 1], found & 0xFFFFFFFF))
        heapq.heapify(queue)
        while queue:
            _, i, left, right, made = heapq.heappop(queue)
            j = after[i]
            if ids[i] != left or j >= n or ids[j] != right:
                continue
            ids[i], ids[j] = made, -1
            j = after[i] = after[j]
            if j < n:
                before[j] = i
                if (found := merges.get(made << 32 | ids[j])) is not None:
                    heapq.heappush(queue, (found >> 32, i, made, ids[j], found & 0xFFFFFFFF))
            h = before[i]
            if h >= 0 and (found := merges.get(ids[h] << 32 | made)) is not None:
                heapq.heappush(queue, (found >> 32, h, ids[h], made, found & 0xFFFFFFFF))
        return [x for x in ids if x >= 0]

    def piece(self, text: str) -> bytes:
        out = np.array(self.merge(text.encode("utf-8")), np.uint32).tobytes()
        if len(text) <= _CACHE_PIECE:
            if len(self.cache) >= _CACHE_ROWS:
                self.cache.clear()
            self.cache[text] = out
        return out

    def encode(self, text: str | None) -> bytes:
        """Ids of a whole text as little-endian unsigned 32-bit integers."""
        if not text:
            return b""
        parts = self.split.split(text) if self.split and self.split.search(text) else [text]
        out: list[bytes] = []
        for part in parts:
            if part in self.added:
                out.append(self.added[part])
                continue
            have = self.cache
            for p in self.pieces.cut(part):
                out.append(have.get(p) or self.piece(p))
        return b"".join(out)

    def decode(self, ids: bytes) -> str:
        """Vocabulary strings one after another; ids that the vocabulary lacks are skipped, broken UTF-8 gives U+FFFD."""
        strings = self.strings
        return b"".join([strings.get(i, b"") for i in np.frombuffer(ids, "<u4").tolist()]).decode("utf-8", "replace")


def tokenizer(path: str, newer: dict[str, str] | None = None) -> ByteBpe:
    """One encoder per Python worker and file."""
    if path not in _TOKENIZERS:
        _TOKENIZERS[path] = ByteBpe(path, newer)
    return _TOKENIZERS[path]


def encode_decode(docs: DataFrame, path: str, keep_text: bool = False) -> DataFrame:
    """Per row of ``docs`` (doc_id, text): doc_id, n_tokens, ids_sha256, decoded_sha256, round_trip.

    Hashes are of the ids as little-endian unsigned 32-bit integers and of the decoded text in UTF-8.
    ``round_trip`` says whether the decoded text is the text. With ``keep_text`` the ids and the decoded text
    follow. Null texts count as empty; rows stay as they are, ties and repeated ones too. Nothing is shuffled:
    a lost task is encoded again from its input split.
    """
    docs = docs.select("doc_id", "text")
    newer = newer_of(path)

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = tokenizer(path, newer)
        for part in slices(batches):
            texts = part.column(1).to_pylist()
            ids = [own.encode(t) for t in texts]
            back = [own.decode(i) for i in ids]
            columns = [
                part.column(0),
                pa.array([len(i) // 4 for i in ids], pa.int64()),
                pa.array([hashlib.sha256(i).hexdigest() for i in ids], pa.string()),
                pa.array([hashlib.sha256(t.encode("utf-8")).hexdigest() for t in back], pa.string()),
                pa.array([(t or "") == b for t, b in zip(texts, back)], pa.bool_()),
            ]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "round_trip"]
            if keep_text:
                columns += [pa.array([np.frombuffer(i, "<u4").astype(np.int64) for i in ids], pa.list_(pa.int64())), pa.array(back, pa.string())]
                names += ["ids", "decoded"]
            yield pa.RecordBatch.from_arrays(columns, names)

    kind = docs.schema["doc_id"].dataType.simpleString()
    more = ", ids array<bigint>, decoded string" if keep_text else ""
    return docs.mapInArrow(run, f"doc_id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string, round_trip boolean{more}")
