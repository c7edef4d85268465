"""Public tokenizers behind small functions; files are named by path and never copied."""

from __future__ import annotations

import base64
import os
import re

import numpy as np

_LOADED: dict = {}
#: Letters for which Python's and the tokenizer's lower case, letter class and composition agree: printable ASCII and Latin letters with marks.
_SAFE = re.compile("[^\x09-\x0d\x20-\x7eÀ-ÖØ-öø-ÿŒœ]")
_PIECE = re.compile("[a-zß-öø-ÿœ]+|[0-9]|'(?:s|t|re|ve|m|ll|d)|[^\\sa-zß-öø-ÿœ0-9]+")


def slices(batches, rows: int = 512):
    """Arrow batches in parts of at most ``rows`` rows, which bounds what one step holds in Python."""
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


def free_name(df, name: str) -> str:
    """``name``, with underscores put before it until no column of ``df`` has it, whatever the case of its letters."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def default_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class WordBpe:
    """Ids of a lower-casing word BPE, equal to the tokenizers library's, with pieces kept in a bounded table.

    The vocabulary splits text into pieces that are encoded apart, and a corpus repeats its pieces: the
    new ones of a batch are encoded by the library once, side by side, and cut after each token that
    ends a word; their ids are kept as bytes. Texts with characters outside ``_SAFE`` or with the text of
    a special token, which is not split, go to the library whole. The table is emptied at ``keep`` pieces.
    """

    def __init__(self, path: str, keep: int = 250_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tok, self.keep, self.known = Tokenizer.from_file(path), keep, {}
        self.special = [t.content.lower() for t in self.tok.get_added_tokens_decoder().values()]
        self.closes = np.zeros(self.tok.get_vocab_size(), dtype=bool)
        self.closes[[i for t, i in self.tok.get_vocab().items() if t.endswith("</w>")]] = True

    def whole(self, text: str) -> bytes:
        return np.asarray(self.tok.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def learn(self, pieces: list[str], step: int = 512) -> None:
        chunks = [pieces[i : i + step] for i in range(0, len(pieces), step)]
        for chunk, got in zip(chunks, self.tok.encode_batch_fast([" ".join(c) for c in chunks], add_special_tokens=False), strict=True):
            ids = np.asarray(got.ids, dtype="<u4")
            ends = (4 * (np.flatnonzero(self.closes[ids]) + 1)).tolist()
            raw = ids.tobytes()
            self.known.update(zip(chunk, [raw[a:b] for a, b in zip([0, *ends], ends, strict=False)], strict=True))

    def ids(self, texts: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        split = [None if _SAFE.search(t) or any(x in low for x in self.special) else _PIECE.findall(low) for t, low in zip(texts, map(str.lower, texts), strict=True)]
        if len(self.known) > self.keep:
            self.known.clear()
        self.learn(list(set().union(*filter(None, split)).difference(self.known)))
        get = self.known.__getitem__
        return [self.whole(t) if p is None else b"".join(map(get, p)) for t, p in zip(texts, split, strict=True)]


def word_bpe(path: str) -> WordBpe:
    if path not in _LOADED:
        _LOADED[path] = WordBpe(path)
    return _LOADED[path]


class ByteBpe:
    """A byte-level BPE given as ranks, with each id's length in bytes, from which offsets follow."""

    def __init__(self, path: str, pattern: str | None = None):
        import tiktoken

        if pattern is None:
            import public_tokenizers

            pattern = public_tokenizers.PATTERN
        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.enc = tiktoken.Encoding("byte", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.width = np.zeros(max(ranks.values()) + 1, dtype=np.int64)
        for token, i in ranks.items():
            self.width[i] = len(token)

    def ends(self, text: str) -> np.ndarray:
        """Byte offset after each token of the whole text."""
        return np.cumsum(self.width[np.asarray(self.enc.encode_ordinary(text), dtype=np.int64)])


def byte_bpe(path: str) -> ByteBpe:
    if path not in _LOADED:
        _LOADED[path] = ByteBpe(path)
    return _LOADED[path]
