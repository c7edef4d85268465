"""Vector bin packing of token sequences under limits on tokens, segments and loss-bearing tokens."""

from __future__ import annotations

import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .vocabulary import default_path, slices, word_bpe


@dataclass
class Packer:
    """Places pieces of documents into sequences by the dot-product heuristic; holds a bounded pool.

    A document's last ``loss`` tokens bear loss. Pieces over a whole sequence are cut off at once. From
    the pool, a sequence takes the piece whose demand (tokens, segments, loss, each over its limit) has
    the largest dot product with what is left of the sequence, among those that fit; when none fits,
    the longest piece is cut to fill it. A sequence closes when it is full or a limit is reached.
    """

    tokens: int = 4096
    segments: int = 1024
    loss: int = 4096
    pool: int = 512
    made: int = 0
    held: list = field(default_factory=list)
    out: list = field(default_factory=list)

    def add(self, name, count: int, loss: int) -> None:
        self.held.append([name, 0, count, count - loss])
        if len(self.held) >= 2 * self.pool:
            self.drain(self.pool)

    def drain(self, keep: int = 0) -> None:
        """Fill sequences while the pool has over ``keep`` pieces and enough tokens for a whole one."""
        self._cut_long()
        n = len(self.held)
        if not n:
            return
        want = np.array([self._demand(h) for h in self.held], dtype=np.float64)
        cap = np.array([self.tokens, self.segments, self.loss], dtype=np.float64)
        alive = np.ones(n, dtype=bool)
        while int(alive.sum()) > keep and want[alive, 0].sum() >= self.tokens and self._fill(cap, want, alive):
            pass
        self.held = [h for h, a in zip(self.held, alive, strict=True) if a]

    def finish(self) -> None:
        """All that is left: full sequences, then the rest in lengths that are powers of two, which need no padding."""
        self.drain()
        rest = sum(end - start for _, start, end, _ in self.held)
        for bit in reversed(range(self.tokens.bit_length())):
            if rest >> bit & 1 and self.held:
                small = Packer(2**bit, self.segments, self.loss, self.pool, self.made, self.held, self.out)
                small.drain()
                self.made, self.held = small.made, small.held
        while self.held:  # limits on segments or loss were in the way
            want = np.array([self._demand(h) for h in self.held], dtype=np.float64)
            alive = np.ones(len(self.held), dtype=bool)
            if not self._fill(np.array([self.tokens, self.segments, self.loss], dtype=np.float64), want, alive):
                raise ValueError("a limit leaves no room for one token")
            self.held = [h for h, a in zip(self.held, alive, strict=True) if a]

    def _demand(self, h) -> tuple[int, int, int]:
        _, start, end, free = h
        return end - start, 1, end - max(start, free) if end > free else 0

    def _cut(self, h, tokens: int, loss: int) -> int:
        """Longest front of a piece within both limits."""
        _, start, end, free = h
        return min(end - start, tokens, max(0, free - start) + loss)

    def _cut_long(self) -> None:
        """Whole sequences are cut off long pieces at once; a piece with more loss than a sequence may hold becomes several, which stay in the pool."""
        whole = []
        for h in self.held:
            while h[2] - h[1] > self.tokens or self._demand(h)[2] > self.loss:
                n = self._cut(h, self.tokens, self.loss)
                if n == self.tokens:
                    self.out.append((h[0], h[1], n, self.made, 0))
                    self.made += 1
                else:
                    whole.append([h[0], h[1], h[1] + n, h[3]])
                h[1] += n
            if h[2] > h[1]:
                whole.append(h)
        self.held = whole

    def _fill(self, cap: np.ndarray, want: np.ndarray, alive: np.ndarray) -> int:
        room, at = cap.copy(), 0
        while alive.any() and room[0] > 0 and room[1] > 0:
            fits = alive & (want <= room).all(axis=1)
            if fits.any():
                i = int(np.argmax(np.where(fits, (want / cap) @ (room / cap), -1)))
                n = int(want[i, 0])
            else:
                i = int(np.argmax(np.where(alive, want[:, 0], -1)))
                n = self._cut(self.held[i], int(room[0]), int(room[2]))
                if n <= 0:
                    break
            h = self.held[i]
            used = self._demand([h[0], h[1], h[1] + n, h[3]])
            self.out.append((h[0], h[1], n, self.made, at))
            h[1] += n
            at += n
            room -= used
            if h[1] == h[2]:
                alive[i] = False
            else:
                want[i] = self._demand(h)
        if at:
            self.made += 1
        return at


def pack_documents(docs: DataFrame, tokenizer_path: str | None = None, id_col: str = "doc_id", text_col: str = "text", prompt_col: str | None = None, end_id: int = 2,
                   tokens: int = 4096, segments: int = 1024, loss: int = 4096, pool: int = 512) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset): the pieces of packed sequences.

    A document is its tokenizer ids and ``end_id``; all but its first id bear loss. With ``prompt_col`` the
    ids of that text stand before them and bear none (null: no prompt). Every partition
    packs its own rows in one pass with a bounded pool, so nothing is shuffled and a lost executor's
    task is simply run again; only a partition's last sequences are short. Sequence ids hold the
    partition above bit 33 and are unique, not gapless. Null text counts as empty (one id); documents
    of any length are cut freely and each id stands in one piece; repeated rows are packed as often; an
    empty table gives none. Further columns are not carried.
    """
    path = tokenizer_path or default_path("word_bpe_49k.json")
    kind = dict(docs.select(id_col).dtypes)[id_col]
    close = np.asarray([end_id], dtype="<u4").tobytes()

    def go(batches):
        bpe, base = word_bpe(path), TaskContext.get().partitionId() << 33
        packer, kept, serial, type_ = Packer(tokens, segments, loss, pool), {}, 0, None

        def flush():
            rows = packer.out
            packer.out = []
            cols = [[] for _ in range(7)]
            for name, start, n, seq, at in rows:
                doc, ids, total, left = kept[name]
                for c, v in zip(cols, (doc, start, n, zlib.crc32(ids[4 * start : 4 * (start + n)]), total, base + seq, at), strict=True):
                    c.append(v)
                if left == n:
                    del kept[name]
                else:
                    kept[name][3] = left - n
            return pa.RecordBatch.from_arrays([pa.array(cols[0], type_), *(pa.array(c, pa.int64()) for c in cols[1:])],
                                              ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

        for part in slices(batches, 384):
            type_ = part.schema.field(0).type
            fronts = bpe.ids(part.column(1).to_pylist()) if prompt_col else [b""] * part.num_rows
            for doc, front, ids in zip(part.column(0).to_pylist(), fronts, bpe.ids(part.column(2).to_pylist()), strict=True):
                n = (len(front) + len(ids)) // 4 + 1
                kept[serial] = [doc, front + ids + close, n, n]
                packer.add(serial, n, n - max(1, len(front) // 4))
                serial += 1
            if packer.out:
                yield flush()
        packer.finish()
        if packer.out:
            yield flush()

    prompt = F.coalesce(prompt_col, F.lit("")) if prompt_col else F.lit("")
    return docs.select(F.col(id_col).alias("doc_id"), prompt.alias("prompt"), F.coalesce(text_col, F.lit("")).alias("text")).mapInArrow(
        go, f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
