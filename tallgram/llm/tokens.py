"""Encoding whole texts with a public tokenizer file, fast enough for whole corpora.

The tokenizer cuts at white space before anything else: its normaliser maps each
white-space run to one space, its splitter never puts white space into a piece,
and neither step looks across it. So ids of a text are the ids of its white-space
separated chunks in order, and a chunk needs encoding once per worker. Chunks are
split and counted by Arrow; only new ones reach the tokenizer.
"""

from __future__ import annotations

import os
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from tallgram.llm.common import LOWER_BYTES, remembered, text_bytes

VOCABULARY = "word_bpe_49k.json"
END_ID = 1
#: Chunks a worker remembers (about 170 bytes each); beyond it those seen in several blocks stay.
MEMORY = 250_000
#: Signs that may end a chunk; the apostrophe, which the splitter treats apart, and parts of special tokens aren't among them.
_TAIL = '.,!?;:*&%$#@^~+=-_/\\()[]{}"`'
#: Last letter of Latin Extended-A.
_LATIN = "\u017f"
_ASCII_BLANKS = bytes(32 if 9 <= i <= 13 else i for i in range(256))
#: Text that a worker encodes at once.
TOKEN_BLOCK_BYTES = 3 << 20


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Encoder:
    """ids of whole texts, each followed by END_ID, as one flat uint32 array with offsets."""

    _open: dict[str, Encoder] = {}

    def __init__(self, path: str, memory: int | None = None):
        self.most = memory
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        # for words of plain lower-case letters the normaliser changes nothing and the splitter keeps them whole
        self.plain = Tokenizer.from_file(path)
        self.plain.normalizer = normalizers.Sequence([])
        self.plain.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        size = self.plain.get_vocab_size()
        self.ends_word = np.fromiter(((self.plain.id_to_token(i) or "").endswith("</w>") for i in range(size)), dtype=bool, count=size)
        self.memory: dict[str, int] = {}  # chunk -> entry; a core is a chunk too
        self._reset()
        mark = self.tokenizer.encode("\x00", add_special_tokens=False).ids
        self.mark = mark[0] if len(mark) == 1 else None

    @classmethod
    def at(cls, path: str, memory: int | None = None) -> Encoder:
        """The worker's encoder of a vocabulary file; memory: chunks it remembers (MEMORY by default)."""
        remembered["tokens"] = cls._open.clear
        if path not in cls._open:
            cls._open[path] = cls(path)
        cls._open[path].most = memory
        return cls._open[path]

    def _reset(self) -> None:
        self.memory.clear()
        self.ids = np.zeros(1 << 19, dtype=np.uint32)
        self.used = 0
        self.starts = np.zeros(1 << 18, dtype=np.int32)
        self.lengths = np.zeros(1 << 18, dtype=np.int32)
        self.seen = np.zeros(1 << 18, dtype=np.int32)  # blocks that had the entry
        self.entries = 0

    def _forget(self) -> None:
        """Keep the entries that most blocks have, at most half of MEMORY."""
        seen = self.seen[: self.entries]
        least = 2
        while np.count_nonzero(seen >= least) > (self.most or MEMORY) // 2:
            least += 1
        keep = np.flatnonzero(seen >= least)
        place = np.full(self.entries, -1, dtype=np.int64)
        place[keep] = np.arange(len(keep))
        names = [(c, int(place[i])) for c, i in self.memory.items() if place[i] >= 0]
        ids, ends = self._gather(keep)
        ids, lengths, seen = ids.copy(), np.diff(ends, prepend=0), seen[keep] - 1
        self._reset()
        self._append(ids, lengths)
        self.seen[: len(keep)] = seen
        self.memory.update(names)

    def _append(self, ids: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Entries of new id runs that stand back to back in ids."""
        need, many = self.used + len(ids), self.entries + len(lengths)
        if need > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros(max(len(self.ids), len(ids)), dtype=np.uint32)])
        if many > len(self.starts):
            more = np.zeros(max(len(self.starts), len(lengths)), dtype=np.int32)
            self.starts, self.lengths, self.seen = (np.concatenate([x, more]) for x in (self.starts, self.lengths, self.seen))
        self.ids[self.used : need] = ids
        self.starts[self.entries : many] = self.used + np.cumsum(lengths) - lengths
        self.lengths[self.entries : many] = lengths
        made = np.arange(self.entries, many)
        self.used, self.entries = need, many
        return made

    def _remember(self, core: str) -> None:
        ids = np.array(self.tokenizer.encode(core, add_special_tokens=False).ids, dtype=np.uint32)
        self.memory[core] = int(self._append(ids, np.array([len(ids)]))[0])

    def _gather(self, runs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """ids of the entries in runs, back to back, and where each run ends."""
        lengths = self.lengths[runs]
        ends = np.cumsum(lengths, dtype=np.int64)
        total = int(ends[-1]) if len(ends) else 0
        shift = self.starts[runs] - (ends - lengths).astype(np.int32)
        return self.ids[np.arange(total, dtype=np.int32) + np.repeat(shift, lengths)], ends

    def _encode_plain(self, words: list[str]) -> None:
        """Many words of plain lower-case letters; an id that ends a word tells where the next begins."""
        coded = self.plain.encode_batch_fast([" ".join(words[i : i + 512]) for i in range(0, len(words), 512)], add_special_tokens=False)
        ids = np.concatenate([np.array(one.ids, dtype=np.uint32) for one in coded])
        lengths = np.diff(np.flatnonzero(self.ends_word[ids]), prepend=-1)
        if len(lengths) != len(words):
            raise ValueError("the tokenizer's words don't end where expected")
        self.memory.update(zip(words, self._append(ids, lengths).tolist(), strict=True))

    def _encode_new(self, cores: list[str]) -> None:
        """Many cores in few calls: plain words by themselves, others with NUL between, those that could disturb that alone."""
        words = [c for c in cores if c.isalpha() and c.islower() and max(c) <= _LATIN]
        if words:
            self._encode_plain(words)
        cores = list(set(cores).difference(words))
        plain = [c for c in cores if "\x00" not in c and "<|" not in c] if self.mark is not None else []
        groups = [plain[i : i + 512] for i in range(0, len(plain), 512)]
        coded = self.tokenizer.encode_batch_fast([" \x00 ".join(g) for g in groups], add_special_tokens=False)
        for group, one in zip(groups, coded, strict=True):
            ids = np.array(one.ids, dtype=np.uint32)
            is_mark = ids == self.mark
            cuts = np.flatnonzero(is_mark)
            if len(cuts) != len(group) - 1:  # ids of a core contain the mark
                for c in group:
                    self._remember(c)
                continue
            lengths = np.diff(np.concatenate([[-1], cuts, [len(ids)]])) - 1
            self.memory.update(zip(group, self._append(ids[~is_mark], lengths).tolist(), strict=True))
        for c in set(cores).difference(plain):
            self._remember(c)

    def _learn(self, chunks: list[str]) -> None:
        trimmed = pc.utf8_rtrim(pa.array(chunks, pa.large_string()), characters=_TAIL).to_pylist()
        parts = [(c, "") if len(c) == len(t) else self._parts(c) for c, t in zip(chunks, trimmed, strict=True)]
        memory = self.memory
        new = {c for c in chain.from_iterable(parts) if c not in memory}
        if new:
            self._encode_new(list(new))
        split = [(c, memory[a], memory[b]) for c, (a, b) in zip(chunks, parts, strict=True) if b]
        if split:
            names, core, tail = zip(*split, strict=True)
            runs = np.empty(2 * len(names), dtype=np.int64)
            runs[0::2], runs[1::2] = core, tail
            ids, ends = self._gather(runs)
            self.memory.update(zip(names, self._append(ids, np.diff(ends[1::2], prepend=0)).tolist(), strict=True))

    @staticmethod
    def _parts(chunk: str) -> tuple[str, str]:
        """A chunk as a core and trailing signs; the splitter cuts there after a letter.

        Only after letters up to the end of Latin Extended-A whose lower case is one
        letter too: others may lower to a letter and a mark, which joins what follows.
        """
        core = chunk.rstrip(_TAIL)
        if len(core) == len(chunk) or not core or core[-1] > _LATIN or not core[-1].lower()[-1].isalpha():
            return chunk, ""
        return core, chunk[len(core) :]

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        if len(self.memory) > (self.most or MEMORY) or self.used > 1 << 30:
            self._forget()
        raw, offsets = text_bytes(column)
        n = len(offsets) - 1
        # the tokenizer lowers letters itself, after composing marks with them and after finding its
        # special tokens; without either in the block, lowering first changes nothing but the number of chunks
        lower_first = b"\xcc" not in raw and b"\xcd" not in raw and b"<|" not in raw
        texts = pa.LargeStringArray.from_buffers(n, pa.py_buffer(offsets.astype(np.int64)), pa.py_buffer(raw.translate(LOWER_BYTES if lower_first else _ASCII_BLANKS)))
        lists = pc.ascii_split_whitespace(texts)
        flat = lists.flatten().dictionary_encode()
        bounds = lists.offsets.to_numpy()
        bounds = bounds - bounds[0]
        chunks = flat.dictionary.to_pylist()
        memory = self.memory
        new = [c for c in chunks if c not in memory]
        if new:
            self._learn(new)
        entry = np.fromiter(map(memory.__getitem__, chunks), dtype=np.int64, count=len(chunks))
        self.seen[entry] += 1
        ids, ends = self._gather(entry[flat.indices.to_numpy()])
        text_ends = np.concatenate([[0], ends])[bounds[1:]]
        out = np.empty(len(ids) + n, dtype=np.uint32)
        stop = text_ends + np.arange(n)
        keep = np.ones(len(out), dtype=bool)
        keep[stop] = False
        out[keep] = ids
        out[stop] = END_ID
        return out, np.concatenate([[0], stop + 1])
