"""Token ids of a public tokenizer file, exactly, a batch of texts at a time.

The tokenizer lower-cases, cuts a text into pieces (runs of letters, single
digits, runs of other signs, a few English endings) and merges inside a piece
only. Texts within Latin-1 are cut as arrays of bytes, all texts of a batch at
once; the pieces are dictionary-encoded by Arrow, only pieces that the worker
has not met go to the BPE model, and the ids are gathered by piece. Other texts
are cut at ASCII white space, which the tokenizer drops and never merges
across, and their words go through the whole tokenizer. A tokenizer file of
another form than this is used as the library has it, without any short cut.
"""

from __future__ import annotations

import json
import os
import unicodedata
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa

END_ID = 1
WORD_FILE = "word_bpe_49k.json"
CACHE_PIECES = 300_000
#: The arrays of a slice take some forty times as many bytes.
SLICE_CHARS = 1_000_000
_SPACE, _LETTER, _DIGIT, _OTHER = range(4)
_BLANKS = b" \t\n\x0b\x0c\r"
# The steps of the tokenizer that the short cut stands for.
_STEPS = ["NFC", "Replace", "Lowercase", "Split", "ByteLevel"]
_CUT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
_WORD_END = "</w>"
# End of fixed values.


def default_tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(WORD_FILE)


def _byte_alphabet() -> str:
    """The printable character that byte-level BPE shows for each byte."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, spare = [], 256
    for byte in range(256):
        if byte in shown:
            out.append(chr(byte))
        else:
            out.append(chr(spare))
            spare += 1
    return "".join(out)


def _kinds() -> bytes:
    """What each Latin-1 character is to the tokenizer's cut."""
    kinds = bytearray()
    for code in range(256):
        group = unicodedata.category(chr(code))[0]
        kinds.append(_SPACE if code in _BLANKS else _LETTER if group == "L" else _DIGIT if group == "N" else _OTHER)
    return bytes(kinds)


_KIND = _kinds()
_LOWER = bytes(ord(low) if len(low := chr(c).lower()) == 1 and ord(low) < 256 else c for c in range(256))
#: Characters whose treatment is the same in every Unicode library: no controls, no other blanks.
_PLAIN = _BLANKS + bytes(range(33, 127)) + bytes(range(161, 256))


def _short_cut_holds(spec: dict) -> bool:
    def steps(part: dict | None, key: str) -> list[dict]:
        return (part or {}).get(key, [part] if part else [])

    before, cut, model = steps(spec["normalizer"], "normalizers"), steps(spec["pre_tokenizer"], "pretokenizers"), spec["model"]
    return (
        [s["type"] for s in before + cut] == _STEPS
        and cut[0]["pattern"] == {"Regex": _CUT}
        and model["type"] == "BPE"
        and model["end_of_word_suffix"] == _WORD_END
        and all(t["content"].startswith("<|") for t in spec["added_tokens"])
    )


def _byte_strings(values: pa.Array) -> list[bytes]:
    """A binary array as Python bytes, without a scalar object for each."""
    _, offsets, data = values.buffers()
    edges = np.frombuffer(offsets, np.int32)[values.offset : values.offset + len(values) + 1].tolist()
    raw = data.to_pybytes()
    return [raw[a:b] for a, b in zip(edges, edges[1:])]


class WordTokenizer:
    """encode(list of texts) -> list of uint32 id arrays, without special tokens."""

    def __init__(self, path: str | None = None, cache_pieces: int = CACHE_PIECES, slice_chars: int = SLICE_CHARS):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, pre_tokenizers

        path = path or default_tokenizer_path()
        self.whole = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            self.short_cut = _short_cut_holds(json.load(f))
        self.cache_pieces, self.slice_chars = cache_pieces, slice_chars
        self.pieces = Tokenizer(self.whole.model)
        self.pieces.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        ends = [i for token, i in self.whole.get_vocab(with_added_tokens=False).items() if token.endswith(_WORD_END)]
        self.is_end = np.zeros(max(self.whole.get_vocab_size() + 1, max(ends, default=0) + 1), bool)
        self.is_end[ends] = True
        alphabet = _byte_alphabet()
        self.shown = {c: "".join(alphabet[b] for b in chr(c).encode()) for c in range(33, 256)}
        self.forget()

    def forget(self) -> None:
        self.codes: dict[bytes, int] = {}
        self.pool = np.zeros(1 << 16, np.uint32)
        self.ends = np.zeros(1 << 14, np.int64)  # ends[c + 1] is where the ids of code c stop in the pool

    # ---- what is known of pieces ----

    def _store(self, keys: list[bytes], ids: np.ndarray, sizes: np.ndarray) -> None:
        first = len(self.codes)
        begin = int(self.ends[first])
        while len(self.pool) < begin + len(ids):
            self.pool = np.concatenate((self.pool, np.zeros_like(self.pool)))
        while len(self.ends) < first + len(keys) + 1:
            self.ends = np.concatenate((self.ends, np.zeros_like(self.ends)))
        self.pool[begin : begin + len(ids)] = ids
        self.ends[first + 1 : first + 1 + len(keys)] = begin + np.cumsum(sizes)
        self.codes.update(zip(keys, range(first, first + len(keys))))

    def _learn_pieces(self, keys: list[bytes]) -> None:
        """Latin-1 pieces, lower case; many on a line, told apart by the ids that end a word."""
        for at in range(0, len(keys), 8192):
            part = keys[at : at + 8192]
            lines = [b" ".join(part[i : i + 128]).decode("latin-1").translate(self.shown) for i in range(0, len(part), 128)]
            ids = np.concatenate([np.asarray(e.ids, np.uint32) for e in self.pieces.encode_batch_fast(lines, add_special_tokens=False)])
            stops = np.flatnonzero(self.is_end[ids]) + 1
            if len(stops) == len(part):
                self._store(part, ids, np.diff(stops, prepend=0))
            else:  # a model that ends pieces in another way
                self._learn_words(part, [k.decode("latin-1") for k in part])

    def _learn_words(self, keys: list[bytes], words: list[str]) -> None:
        found = [np.asarray(e.ids, np.uint32) for e in self.whole.encode_batch(words, add_special_tokens=False)]
        self._store(keys, np.concatenate(found), np.fromiter(map(len, found), np.int64, len(found)))

    def _gather(self, codes: np.ndarray, doc_stops: np.ndarray) -> list[np.ndarray]:
        """Ids of each document; doc_stops counts the pieces up to each document's end."""
        begins = self.ends[codes]
        sizes = self.ends[codes + 1] - begins
        after = np.cumsum(sizes)
        flat = self.pool[np.repeat(begins - (after - sizes), sizes) + np.arange(after[-1] if len(after) else 0)]
        edges = np.concatenate(([0], after))[doc_stops].tolist()
        return [flat[a:b] for a, b in zip([0, *edges[:-1]], edges)]

    # ---- two ways to cut ----

    def _plain(self, texts: list[bytes]) -> list[np.ndarray]:
        """Texts of plain Latin-1 characters, as Latin-1 bytes."""
        joined = b"\n".join([*texts, b"\n"]).translate(_LOWER)
        kind = np.frombuffer(joined.translate(_KIND), np.uint8)
        raw = np.frombuffer(joined, np.uint8)
        first = np.empty(len(raw), bool)
        first[0] = True
        np.not_equal(kind[1:], kind[:-1], out=first[1:])
        first |= kind == _DIGIT
        marks = np.flatnonzero(raw[:-2] == ord("'"))
        if len(marks):
            marks = marks[first[marks]]
            one, two = raw[marks + 1], raw[marks + 2]
            short = np.isin(one, list(b"stmd"))
            long = ((one == ord("r")) | (one == ord("v"))) & (two == ord("e")) | (one == ord("l")) & (two == ord("l"))
            first[marks[short | long] + 1] = False
            first[marks[short] + 2] = True
            first[marks[long] + 3] = True
        keep = kind != _SPACE
        first &= keep
        stops = np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)) + 1) - 1
        doc_stops = np.searchsorted(np.flatnonzero(first), stops)
        data = raw[keep]
        offsets = np.flatnonzero(first[keep]).astype(np.int32)
        n = len(offsets)
        if not n:
            return [np.zeros(0, np.uint32)] * len(texts)
        edges = np.append(offsets, np.int32(len(data)))
        cut = pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(edges), pa.py_buffer(data)]).dictionary_encode()
        met = _byte_strings(cut.dictionary)
        known = self.codes
        missing = [p for p in met if p not in known]
        if missing:
            self._learn_pieces(missing)
        codes = np.fromiter(map(known.__getitem__, met), np.int64, len(met))
        return self._gather(codes[cut.indices.to_numpy()], doc_stops)

    def _any(self, texts: list[str]) -> list[np.ndarray]:
        """Any text: words through the whole tokenizer. A key starts with a zero byte, which no plain piece holds."""
        split = [[b"\0" + w for w in text.encode("utf-8", "replace").split()] for text in texts]
        known = self.codes
        missing = [w for w in set().union(*split) if w not in known]
        if missing:
            self._learn_words(missing, [w[1:].decode() for w in missing])
        codes = np.array([known[w] for words in split for w in words], np.int64)
        return self._gather(codes, np.cumsum([len(words) for words in split]))

    def _cut_long(self, text: str) -> list[str]:
        """Parts of a bounded length, cut at ASCII white space."""
        parts, at = [], 0
        while len(text) - at > self.slice_chars:
            stop = max(text.rfind(blank, at, at + self.slice_chars) for blank in _BLANKS.decode())
            if stop <= at:
                break
            parts.append(text[at:stop])
            at = stop
        return [*parts, text[at:]]

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        if not self.short_cut:
            return [np.asarray(e.ids, np.uint32) for e in self.whole.encode_batch(texts, add_special_tokens=False)]
        parts = [(i, part) for i, text in enumerate(texts) for part in self._cut_long(text)]
        found: list[list[np.ndarray]] = [[] for _ in texts]
        at = 0
        while at < len(parts):
            stop, size = at, 0
            while stop < len(parts) and (stop == at or size + len(parts[stop][1]) <= self.slice_chars):
                size += len(parts[stop][1])
                stop += 1
            for i, ids in self._slice(parts[at:stop]):
                found[i].append(ids)
            at = stop
        return [f[0] if len(f) == 1 else np.concatenate(f) for f in found]

    def _slice(self, parts: list[tuple[int, str]]) -> Iterator[tuple[int, np.ndarray]]:
        if len(self.codes) > self.cache_pieces:
            self.forget()
        plain, other, is_plain = [], [], []
        for _, text in parts:
            try:
                raw = text.encode("latin-1")
            except UnicodeEncodeError:
                raw = None
            # "<|" may begin a special token, which is matched before lower-casing
            fits = raw is not None and not raw.translate(None, _PLAIN) and b"<|" not in raw
            is_plain.append(fits)
            (plain if fits else other).append(raw if fits else text)
        found = {True: iter(self._plain(plain) if plain else ()), False: iter(self._any(other) if other else ())}
        for (i, _), fits in zip(parts, is_plain):
            yield i, next(found[fits])


_TOKENIZERS: dict[str, WordTokenizer] = {}


def tokenizer(path: str | None = None) -> WordTokenizer:
    """One tokenizer per worker process."""
    key = path or ""
    if key not in _TOKENIZERS:
        _TOKENIZERS[key] = WordTokenizer(path)
    return _TOKENIZERS[key]


def forget_pieces() -> None:
    """Frees what the worker's tokenizers know of pieces, which a reused worker would otherwise keep."""
    for known in _TOKENIZERS.values():
        known.forget()


def crc32_ids(ids: np.ndarray) -> int:
    return zlib.crc32(np.ascontiguousarray(ids, "<u4").tobytes())


def encoded_slices(batches: Iterable, path: str | None, columns: tuple[str, ...] = ("doc_id",), rows: int = 2000, chars: int = SLICE_CHARS) -> Iterator[tuple[list[list], list[np.ndarray]]]:
    """Arrow batches with a text column -> (other columns' values, ids with the end id), a bounded slice at a time."""
    encoder = tokenizer(path)
    for batch in batches:
        lengths = np.asarray(batch.column("chars").to_pylist() if "chars" in batch.schema.names else [0] * batch.num_rows, np.int64)
        at = 0
        while at < batch.num_rows:
            total = np.cumsum(lengths[at : at + rows])
            take = max(1, int(np.searchsorted(total, chars, "right")))
            part = batch.slice(at, take)
            texts = [t or "" for t in part.column("text").to_pylist()]
            ids = [np.append(x, np.uint32(END_ID)) for x in encoder.encode(texts)]
            yield [part.column(c).to_pylist() for c in columns], ids
            at += part.num_rows
