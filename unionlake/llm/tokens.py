"""Token ids of whole texts by a public tokenizer file, many texts at a time.

The word_bpe vocabulary lower-cases a text, cuts it into words by classes of characters and merges
bytes inside words. Here one pass over the bytes of many texts finds the words, Arrow numbers the
distinct ones, their merges are done together, and the ids of all texts are gathered from theirs,
so nothing is remembered between batches. Pieces (between blanks) with characters beyond printable
ASCII and plain Latin letters go through the library, texts that spell a special token go through
it whole, and so do all texts of a vocabulary file with other settings. Tests hold this against the
library on whole texts.
"""

from __future__ import annotations

import json
import os
import sys
from array import array
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from unionlake.llm.merges import WIDTHS, Merges

#: The settings of a vocabulary file that this module follows.
NORMALIZERS = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
WORD_END = "</w>"

BLANK, LETTER, DIGIT, OTHER, STRANGE = range(5)
CHUNK = 1 << 22


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def known_settings(settings: dict) -> bool:
    steps = (settings.get("pre_tokenizer") or {}).get("pretokenizers") or []
    model = settings["model"]
    return (
        (settings.get("normalizer") or {}).get("normalizers") == NORMALIZERS
        and [s.get("type") for s in steps] == ["Split", "ByteLevel"]
        and (steps[0]["pattern"], steps[0]["behavior"], steps[0]["invert"]) == ({"Regex": PATTERN}, "Removed", True)
        and not steps[1]["add_prefix_space"] and not steps[1]["use_regex"]
        and model["type"] == "BPE" and model.get("end_of_word_suffix") == WORD_END
        and not any(model.get(k) for k in ("continuing_subword_prefix", "dropout", "unk_token", "byte_fallback", "ignore_merges"))
        and not any(settings.get(k) for k in ("truncation", "padding", "post_processor"))
    )


def byte_letters() -> list[str]:
    """How the vocabulary spells bytes: printable ones as themselves, the others from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spelt = {b: chr(b) for b in plain}
    for b in range(256):
        if b not in spelt:
            spelt[b] = chr(256 + len(spelt) - len(plain))
    return [spelt[b] for b in range(256)]


def byte_classes() -> np.ndarray:
    """The class of each byte by itself; what Latin letters of two bytes are is seen in context."""
    out = np.full(256, STRANGE, np.uint8)
    out[33:127] = OTHER
    out[[9, 10, 11, 12, 13, 32]] = BLANK
    for first, last, kind in ((b"a", b"z", LETTER), (b"A", b"Z", LETTER), (b"0", b"9", DIGIT)):
        out[first[0] : last[0] + 1] = kind
    return out


CLASSES = byte_classes()
LOWER = np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)], np.uint8)
#: What may follow an apostrophe that begins a word, and is a word with it.
SHORT = [(b"s",), (b"t",), (b"m",), (b"d",), (b"r", b"e"), (b"v", b"e"), (b"l", b"l")]


def words(text: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Words in the bytes of texts that blanks part: their bytes in lower case one after another, where each word
    begins in `text`, and how long it is. A piece with a strange byte is one word, as it stands."""
    kind = CLASSES[text]
    low = LOWER[text]
    lead = np.flatnonzero(text[:-1] == 0xC3)
    follow = text[lead + 1]
    latin = (follow != 0x97) & (follow != 0xB7)
    lead, follow = lead[latin], follow[latin]
    kind[lead] = kind[lead + 1] = LETTER
    low[lead + 1] = np.where(follow < 0x9F, follow + 0x20, follow)
    begins = np.empty(len(text), bool)
    begins[0] = True
    np.not_equal(kind[1:], kind[:-1], out=begins[1:])
    quote = np.flatnonzero((low == 0x27) & begins)
    begins |= kind == DIGIT
    if len(quote):
        after = np.concatenate((low, np.zeros(2, np.uint8)))
        for ending in SHORT:
            hit = quote
            for i, c in enumerate(ending, 1):
                hit = hit[after[hit + i] == c[0]]
            begins[hit + 1] = False
            stop = hit + 1 + len(ending)
            begins[stop[stop < len(text)]] = True
    if (kind == STRANGE).any():
        blank = kind == BLANK
        edge = ~blank
        edge[1:] &= blank[:-1]
        piece = np.cumsum(edge, dtype=np.int32)
        odd = np.zeros(int(piece[-1]) + 1, bool)
        odd[piece[kind == STRANGE]] = True
        odd = odd[piece] & ~blank
        begins = np.where(odd, edge, begins)
        low = np.where(odd, text, low)
    inside = kind != BLANK
    begins &= inside
    starts = np.flatnonzero(begins)
    number = np.cumsum(begins, dtype=np.int32)[inside]
    return low[inside], starts, np.bincount(number, minlength=len(starts) + 1)[1:]


class Encoder:
    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        if array("I").itemsize != 4 or sys.byteorder != "little":
            raise RuntimeError("ids need 32-bit little-endian integers")
        self.lib = Tokenizer.from_file(path)
        self.special = [t.content for t in self.lib.get_added_tokens_decoder().values()]
        with open(path, encoding="utf-8") as f:
            settings = json.load(f)
        model, letters = settings["model"], byte_letters()
        self.in_words = known_settings(settings) and all(x in model["vocab"] and x + WORD_END in model["vocab"] for x in letters)
        if self.in_words:
            vocab = model["vocab"]
            pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
            self.inner, self.final = (np.array([vocab[x + end] for x in letters], np.int32) for end in ("", WORD_END))
            self.merges = Merges([(vocab[a], vocab[b], vocab[a + b]) for a, b in pairs], int(max(self.inner.max(), self.final.max())) + 1)

    def whole(self, text: str) -> np.ndarray:
        return np.array(self.lib.encode(text, add_special_tokens=False).ids, np.uint32)

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of a column of texts as one array, and where each text's begin, with the end; a null is empty."""
        texts = pc.fill_null(texts, "")
        apart = np.full(len(texts), not self.in_words)
        for s in self.special:
            apart |= pc.match_substring(texts, s).to_numpy(zero_copy_only=False)
        if not apart.any():
            return self._encode(texts)
        ids, bounds = self._encode(pc.if_else(pa.array(apart), "", texts))
        parts, sizes, at = [], np.diff(bounds), 0
        for i in np.flatnonzero(apart).tolist():
            own = self.whole(texts[i].as_py())
            parts += [ids[at : bounds[i]], own]
            sizes[i], at = len(own), bounds[i]
        return np.concatenate([*parts, ids[at:]]), np.concatenate(([0], np.cumsum(sizes)))

    def _encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        raw = texts.cast(pa.binary())
        joined = b" ".join(raw.to_pylist())
        firsts = np.cumsum(pc.binary_length(raw).to_numpy(zero_copy_only=False).astype(np.int64) + 1)
        ids, places, counts, low = [np.zeros(0, np.uint32)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], 0
        while low < len(joined):
            high = low + CHUNK
            if high < len(joined):  # the next blank ends the chunk: a vertical tab or form feed may stand inside one
                ends = [e for e in (joined.find(c, high) for c in (b" ", b"\n", b"\t", b"\r")) if e >= 0]
                high = min(ends, default=len(joined))
            own, starts, sizes = self._chunk(joined[low:high])
            ids.append(own)
            places.append(starts + low)
            counts.append(sizes)
            low = high
        ends = np.concatenate(([0], np.cumsum(np.concatenate(counts))))
        bounds = np.searchsorted(np.concatenate(places), np.concatenate(([0], firsts)))
        return np.concatenate(ids), ends[bounds]

    def _chunk(self, text: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The ids of all words, where the words begin, and how many ids each has."""
        raw, starts, lengths = words(np.frombuffer(text, np.uint8))
        if not len(starts):
            return np.zeros(0, np.uint32), starts, lengths
        offsets = np.zeros(len(starts) + 1, np.int32)
        np.cumsum(lengths, out=offsets[1:])
        coded = pa.Array.from_buffers(pa.binary(), len(starts), [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(raw))]).dictionary_encode()
        distinct = coded.dictionary
        at, size = coded.indices.to_numpy(), pc.binary_length(distinct).to_numpy().astype(np.int64)
        data = np.frombuffer(distinct.buffers()[2] or b"", np.uint8)[: int(size.sum())]
        begins = np.cumsum(size) - size
        symbols = self.inner[data]
        symbols[begins + size - 1] = self.final[data[begins + size - 1]]
        kind = CLASSES[data]
        lead = np.flatnonzero(data[:-1] == 0xC3)
        lead = lead[(data[lead + 1] != 0x97) & (data[lead + 1] != 0xB7)]
        kind[lead] = kind[lead + 1] = LETTER
        odd = np.zeros(len(size), bool)
        odd[np.searchsorted(begins, np.flatnonzero(kind == STRANGE), "right") - 1] = True
        odd |= size > WIDTHS[-1]
        ids, counts = self.merges.apply(symbols, begins, np.where(odd, 0, size))
        if odd.any():
            which = np.flatnonzero(odd)
            own = [self.whole(distinct[i].as_py().decode()) for i in which.tolist()]
            before = np.concatenate(([0], np.cumsum(counts)))[which]
            counts[which] = list(map(len, own))
            ids = np.insert(ids, np.repeat(before, counts[which]), np.concatenate(own))
        sizes = counts[at]
        where = np.repeat((np.cumsum(counts) - counts)[at] - (np.cumsum(sizes) - sizes), sizes)
        where += np.arange(len(where))
        return ids[where], starts, sizes


@cache
def encoder(path: str) -> Encoder:
    """One for each Python worker, kept over its tasks."""
    return Encoder(path)


def with_end(ids: np.ndarray, bounds: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """The ids with end_id after each text's, and where each text's begin, with the end."""
    return np.insert(ids, bounds[1:], np.uint32(end_id)), bounds + np.arange(len(bounds))
