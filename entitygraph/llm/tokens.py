"""Token ids of whole texts with a public tokenizer, a dictionary of words at a time."""

from __future__ import annotations

import ctypes
import gc
import json
import os
from collections.abc import Iterator
from contextlib import suppress

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: What a tokenizer's file must state for texts to be put together from words (fixed values): lower case, white space dropped, each part with a word end.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
NORMALISER = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]
PRE_TOKENISER = [
    {"type": "Split", "pattern": {"Regex": SPLIT}, "behavior": "Removed", "invert": True},
    {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
]
#: Words of these characters are cut by the split pattern outside the tokenizer; no normalisation but lower case changes them.
PLAIN = "^[\x21-\x7e¡-įı-ɏ]*$"
#: Texts of about so many bytes are handled together; so many where only their words are looked up.
BLOCK, WORD_BLOCK = 4_000_000, 6_000_000
#: Parts of words kept per worker; beyond it the dictionary starts anew.
PARTS = 400_000


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _by_words(path: str) -> bool:
    """Whether the file's own normaliser, pre-tokenizer and model are those that words can be encoded one by one with."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    model = spec["model"]
    plain = not any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "byte_fallback", "ignore_merges"))
    return (
        (spec.get("normalizer") or {}).get("normalizers") == NORMALISER
        and (spec.get("pre_tokenizer") or {}).get("pretokenizers") == PRE_TOKENISER
        and model.get("type") == "BPE" and model.get("end_of_word_suffix") == "</w>" and plain
        and not spec.get("post_processor") and all(t["content"].startswith("<|") for t in spec.get("added_tokens") or [])
    )


class WordEncoder:
    """Encodes white-space separated words once each and puts texts together from them.

    The tokenizer drops white space and never joins what it separates, so a text's ids are those of its words in a row. A word
    of plain letters, digits and signs is cut by the tokenizer's own split pattern, and its parts, which each end in a word-end
    token, are encoded together, once each; any other word (other alphabets, control characters, special tokens) goes through the whole tokenizer.
    So does every text where the tokenizer's file does not state these rules."""

    def __init__(self, path: str):
        os.environ["RAYON_NUM_THREADS"] = "1"
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.whole = Tokenizer.from_file(path)
        vocab = self.whole.get_vocab()
        self.size = max(vocab.values()) + 1
        self.kind = np.dtype("<u2" if self.size <= 1 << 16 else "<u4")
        self.by_words = _by_words(path)
        if self.by_words:
            self.parts = Tokenizer.from_file(path)
            self.parts.normalizer = normalizers.Sequence([])
            self.parts.pre_tokenizer = pre_tokenizers.Sequence(
                [pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, trim_offsets=True, use_regex=False)]
            )
            self.ends = np.zeros(self.size, bool)
            self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
            self.clear()

    def clear(self) -> None:
        """Part 0 is the empty one."""
        self.known: dict[str, int] = {"": 0}
        self.pool = np.empty(1 << 20, self.kind)
        self.starts, self.n = np.zeros(1 << 16, np.int64), 1  # in bytes; part i lies from starts[i] to starts[i + 1]

    def _lists(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(x.ids, self.kind) for x in self.whole.encode_batch_fast(texts, add_special_tokens=False)] if texts else []

    def _add(self, sizes: np.ndarray, ids: np.ndarray) -> None:
        """Ids of further parts, at the end of the pool."""
        step, at = self.kind.itemsize, int(self.starts[self.n])
        while len(self.starts) <= self.n + len(sizes):
            self.starts = np.concatenate([self.starts, np.zeros_like(self.starts)])
        self.starts[self.n + 1 : self.n + len(sizes) + 1] = at + np.cumsum(sizes) * step
        while len(self.pool) * step < at + len(ids) * step:
            self.pool = np.concatenate([self.pool, np.empty_like(self.pool)])
        self.pool[at // step : at // step + len(ids)] = ids
        self.n += len(sizes)

    def _learn(self, new: list[str]) -> None:
        for at in range(0, len(new), 20_000):
            some = new[at : at + 20_000]
            ids = np.array(self.parts.encode_batch_fast([" ".join(some)], add_special_tokens=False)[0].ids, self.kind)
            cuts = np.flatnonzero(self.ends[ids]) + 1
            if len(cuts) != len(some):  # an unknown character, say: each by itself
                lists = self._lists(some)
                self._add(np.array([len(x) for x in lists], np.int64), np.concatenate(lists))
            else:
                self._add(np.diff(cuts, prepend=0), ids[: cuts[-1]])
            first = self.n - len(some)
            self.known.update(zip(some, range(first, self.n), strict=True))

    def _binary(self, offsets: np.ndarray, data) -> pa.Array:
        return pa.Array.from_buffers(pa.large_binary(), len(offsets) - 1, [None, pa.py_buffer(np.ascontiguousarray(offsets, np.int64)), pa.py_buffer(data)])

    def _easy(self, words: pa.Array) -> pa.Array:
        """The ids of plain words, as bytes. One of letters alone is its own only part."""
        low, letters = pc.utf8_lower(words), pc.ascii_is_alpha(words)
        spaced = pc.replace_with_mask(low, pc.invert(letters), pc.replace_substring_regex(low.filter(pc.invert(letters)), f"({SPLIT})", r"\1 "))
        lists = pc.split_pattern(spaced, " ")  # with empty parts at ends
        borders = lists.offsets.to_numpy()
        coded = lists.flatten().dictionary_encode()
        parts = coded.dictionary.to_pylist()
        if len(self.known) + len(parts) > PARTS:
            self.clear()
        known = self.known
        self._learn([p for p in parts if p not in known])
        table = self._binary(self.starts[: self.n + 1], self.pool)
        index = np.fromiter(map(known.__getitem__, parts), np.int64, len(parts))
        flat = table.take(pa.array(index)).take(coded.indices)
        at = np.frombuffer(flat.buffers()[1], np.int64, len(flat) + 1)
        return self._binary(at[borders - borders[0]], flat.buffers()[2])

    def _words(self, words: pa.Array) -> pa.Array:
        plain = pc.and_(pc.match_substring_regex(words, PLAIN), pc.invert(pc.match_substring(words, "<|")))
        out = self._easy(words.filter(plain))
        if len(out) == len(words):
            return out
        lists = self._lists(words.filter(pc.invert(plain)).to_pylist())
        hard = self._binary(np.cumsum([0, *map(len, lists)]) * self.kind.itemsize, np.concatenate(lists))
        mask = plain.to_numpy(zero_copy_only=False)
        place = np.where(mask, np.cumsum(mask) - 1, len(out) + np.cumsum(~mask) - 1)
        return pa.concat_arrays([out, hard]).take(pa.array(place))

    def encode(self, texts: pa.Array, end_id: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(offsets, ids): the ids of text i are ids[offsets[i]:offsets[i + 1]], with the end id last where one is given."""
        kind = self.kind if end_id is None or end_id < 1 << 8 * self.kind.itemsize else np.dtype("<u4")
        texts = texts.fill_null("").cast(pa.large_string())
        if not self.by_words or kind != self.kind:
            lists = [x.astype(kind) for x in self._lists(texts.to_pylist())]
            lists = lists if end_id is None else [np.append(x, kind.type(end_id)) for x in lists]
            return np.cumsum([0, *map(len, lists)]), np.concatenate([np.empty(0, kind), *lists])
        lists = pc.split_pattern(pc.replace_substring(texts, "\n", " "), " ")
        borders = lists.offsets.to_numpy()
        borders = borders - borders[0]
        coded = lists.flatten().dictionary_encode()
        words, codes = self._words(coded.dictionary), coded.indices.to_numpy()
        if end_id is not None:
            codes = np.insert(codes, borders[1:], len(words))
            borders = borders + np.arange(len(borders))
            words = pa.concat_arrays([words, pa.array([np.array([end_id], kind).tobytes()], pa.large_binary())])
        flat = words.take(pa.array(codes))
        at = np.frombuffer(flat.buffers()[1], np.int64, len(flat) + 1)[borders] // kind.itemsize
        return at, np.frombuffer(flat.buffers()[2], kind, int(at[-1])) if len(flat) and at[-1] else np.empty(0, kind)


def blocks(batch: pa.RecordBatch, column: int, size: int = BLOCK) -> Iterator[pa.RecordBatch]:
    """Slices of a batch whose texts have about ``size`` bytes."""
    sizes = np.cumsum(pc.binary_length(batch.column(column)).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64))
    row = 0
    while row < batch.num_rows:
        done = sizes[row - 1] if row else 0
        last = max(row + 1, int(np.searchsorted(sizes, done + size, "right")))
        yield batch.slice(row, last - row)
        row = last


_encoders: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


def forget_encoders() -> None:
    """Gives a worker's dictionaries back to the system, some 300 MB each, in a step that has no texts to encode: Spark hands its workers on from step to step."""
    if _encoders:
        _encoders.clear()
        gc.collect()
        pa.default_memory_pool().release_unused()
        with suppress(OSError, AttributeError):  # C libraries without it keep what they freed
            ctypes.CDLL(None).malloc_trim(0)
