"""Vocabulary files of public byte-level tokenizers, and encoders that workers load once and keep."""

from __future__ import annotations

import base64
import functools
import os

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

RANKS = "byte_bpe_50k.tiktoken"
VOCAB = "byte_bpe_50k.json"
END_ID = 2


def default_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def default_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


@functools.lru_cache(maxsize=4)
def rank_encoder(path: str, pattern: str):
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
    return tiktoken.Encoding(os.path.basename(path), pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


class PieceEncoder:
    """Ids by the tokenizers library, with a bounded memory of pieces.

    A blank before a character that is not white space always begins a pre-token, and what stands before it never depends on
    what follows, so a text falls into pieces there that can be encoded apart.  The distinct pieces of some texts are found by
    Arrow; those not in memory go to the library together.  Pieces that were not asked for lately are forgotten.

    ``ordinary``: names of the vocabulary's added tokens in a text are ordinary text.  Else they are those tokens, as the library has it
    by default; a text that names one goes to the library whole, since a blank before it need not begin a pre-token."""

    #: Pieces in memory before those asked for least are forgotten, and after.
    MOST, LEFT = 400_000, 150_000
    #: Characters that are encoded together, but for longer texts.
    TOGETHER = 1 << 20

    def __init__(self, path: str, ordinary: bool = True):
        import re

        from tokenizers import Tokenizer

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = ordinary
        self.added = [] if ordinary else [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        vocab = self.tokenizer.get_vocab()
        self.dtype = np.dtype("<u4" if max(vocab.values()) > 65_535 else "<u2")
        #: a byte-level vocabulary spells each byte of a token as one character
        self.n_bytes = np.zeros(max(vocab.values()) + 1, np.int64)
        for token, i in vocab.items():
            self.n_bytes[i] = len(token)
        # every code point that any definition of white space names stays inside a piece
        space = "".join(map(chr, [*range(0x09, 0x0E), *range(0x1C, 0x21), 0x85, 0xA0, 0x1680, 0x180E, *range(0x2000, 0x200C), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000, 0xFEFF]))
        self.cut, self.space = re.compile(f" (?=[^{re.escape(space)}])"), pa.array(["", *space], pa.large_string())
        self._forget(None)

    def _forget(self, keep: np.ndarray | None) -> None:
        """The memory: pieces, where their ids begin in ``flat``, how many there are, and how often they were asked for."""
        if keep is None:
            self.names, self.start, self.size, self.asked, self.flat = pa.array([], pa.large_string()), *(np.zeros(0, np.int64) for _ in range(3)), np.zeros(0, self.dtype)
            return
        self.names, size = self.names.take(pa.array(keep)), self.size[keep]
        self.flat = self._gather(self.start[keep], size)
        self.start, self.size, self.asked = np.cumsum(size) - size, size, self.asked[keep] // 2

    def _gather(self, start: np.ndarray, size: np.ndarray) -> np.ndarray:
        at = np.cumsum(size) - size
        return self.flat[np.arange(int(size.sum())) - np.repeat(at - start, size)]

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text as little-endian unsigned integers of ``dtype``."""
        out, some, size = [], [], 0
        for t in texts:
            some.append(t)
            size += len(t)
            if size >= self.TOGETHER:
                out += self._some(some)
                some, size = [], 0
        return out + self._some(some)

    def _learn(self, pieces: pa.Array) -> np.ndarray:
        """Places in memory of distinct pieces, each encoded with a blank before it."""
        if len(self.names) > self.MOST:
            self._forget(np.sort(np.argpartition(-self.asked, self.LEFT)[: self.LEFT]))
        found = pc.index_in(pieces, self.names) if len(self.names) else pa.nulls(len(pieces), pa.int32())
        missing = pieces.filter(found.is_null())
        if len(missing):
            joined = " " + " ".join(missing.to_pylist())
            ids = np.array(self.tokenizer.encode_batch_fast([joined], add_special_tokens=False)[0].ids, self.dtype)
            ends = np.cumsum(pc.binary_length(missing).to_numpy() + 1)
            cuts = np.searchsorted(np.cumsum(self.n_bytes[ids]), ends, side="right")
            start = np.r_[0, cuts[:-1]]
            self.start, self.size = np.r_[self.start, len(self.flat) + start], np.r_[self.size, cuts - start]
            self.asked, self.flat = np.r_[self.asked, np.zeros(len(missing), np.int64)], np.concatenate([self.flat, ids])
            known = len(self.names)
            self.names = pa.concat_arrays([self.names, missing])
            place = found.fill_null(-1).to_numpy().astype(np.int64)
            place[place < 0] = known + np.arange(len(missing))
            return place
        return found.to_numpy().astype(np.int64)

    def _some(self, texts: list[str]) -> list[bytes]:
        if not texts:
            return []
        whole = {i for i, t in enumerate(texts) if any(x in t for x in self.added)}
        split = pc.split_pattern(pa.array(["" if i in whole else t for i, t in enumerate(texts)], pa.large_string()), " ")
        flat, bounds = split.flatten(), split.offsets.to_numpy()
        first = np.zeros(len(flat), bool)
        first[bounds[:-1]] = True
        # a piece that begins with white space belongs to the one before; texts with such pieces are cut one by one
        inner = pc.is_in(pc.utf8_slice_codeunits(flat, 0, 1), self.space).to_numpy(zero_copy_only=False) & ~first
        cut = {i: self.cut.split(texts[i]) for i in np.flatnonzero(np.add.reduceat(inner, bounds[:-1])).tolist()}
        odd = np.isin(np.arange(len(texts)), list(cut))
        flat = flat.filter(pa.array(~(first | np.repeat(odd, np.diff(bounds)))))
        n = np.where(odd, 0, np.diff(bounds) - 1)
        if cut:
            # the pieces of those texts come after all others
            flat = pa.concat_arrays([flat, pa.array([p for x in cut.values() for p in x[1:]], pa.large_string())])
        # what stands before the first blank is encoded by itself
        heads = [texts[i] if i in whole else cut[i][0] if i in cut else t.split(" ", 1)[0] for i, t in enumerate(texts)]
        heads = self.tokenizer.encode_batch_fast(heads, add_special_tokens=False)
        coded = flat.dictionary_encode()
        index = coded.indices.to_numpy()
        place = self._learn(coded.dictionary)[index] if len(index) else np.zeros(0, np.int64)
        np.add.at(self.asked, place, 1)
        size = self.size[place]
        ids = self._gather(self.start[place], size)
        ends = np.r_[0, np.cumsum(size)]
        begin = np.cumsum(n) - n
        if cut:
            many = np.array([len(x) - 1 for x in cut.values()])
            begin[odd], n[odd] = n.sum() + np.cumsum(many) - many, many
        return [np.array(h.ids, self.dtype).tobytes() + ids[a:b].tobytes() for h, a, b in zip(heads, ends[begin].tolist(), ends[begin + n].tolist())]


@functools.lru_cache(maxsize=2)
def piece_encoder(path: str) -> PieceEncoder:
    return PieceEncoder(path, ordinary=False)
