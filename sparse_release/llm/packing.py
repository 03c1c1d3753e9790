"""Hierarchical multi-length packing of token sequences.

Documents are routed by length to tiers, windows of 2^k tokens up to the longest; each tier opens windows for its fragments, from the longest tier down, and what
a window lacks comes from shorter tiers, best fit first, and at last from a cut fragment, so windows leave the packer full. What remains at the end of a group is
laid out in ever smaller powers of two, which need no padding. Windows are then gathered into step groups of equal tokens.

Tokens come from a public word-end vocabulary whose pieces never cross blanks, so each distinct word is encoded once and remembered (a bounded memory).
Documents are packed where they lie, in groups of bounded tokens: nothing is shuffled, and a lost executor costs its own tasks.

Null or empty text: only the closing token. Texts of any length are cut into full windows. Repeated rows and ids are packed each for itself; an empty table gives
no pieces. Other columns do not matter.
"""

from __future__ import annotations

import bisect
import os
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SHORT_WORD, spelled_alike, word_hashes, word_spans

SEQ_LEN, SHORTEST_TIER = 4096, 512
#: Tokens packed together, tokens of a step group, words remembered by one worker.
GROUP_TOKENS, STEP_TOKENS, REMEMBERED = 4_000_000, 65_536, 800_000
#: Texts that are encoded together: a worker keeps the memory that so many need at their peak for as long as it lives.
TEXTS = 256

_PIECE = "{name} {kind}, start long, length long, ids binary, doc_tokens long, sequence_id long, offset long, tier int, step long"


# What a word may end in, by its last bytes, before signs that no piece of the vocabulary joins to it: an ASCII letter or digit, or a letter of U+00C0 to U+00FF.
_SIGN, _ALNUM = np.zeros(256, bool), np.zeros(256, bool)
_SIGN[list(b".,;:!?*#$%&")] = True
_ALNUM[[c for c in range(128) if chr(c).isalnum()]] = True


class Encoder:
    """Texts to little-endian 32-bit ids, by words.

    The vocabulary's pieces are lower-case, and change at each border of letters and other characters; so words are taken in lower case, and the signs that many
    end in are words of their own. Far fewer of these are distinct, and each is encoded when it is first met. They are told apart by 64-bit hashes.
    """

    def __init__(self, path: str, end_id: int) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer, self.end, self.known = Tokenizer.from_file(path), end_id.to_bytes(4, "little"), {}

    def __call__(self, texts: list[str | None]) -> list[bytes]:
        coded = [(t or "").encode() for t in texts]
        raw = b"".join(coded).lower()
        bounds = np.concatenate(([0], np.cumsum([len(c) for c in coded], dtype=np.int64)))
        buf = np.frombuffer(raw, np.uint8)
        starts, ends = _parted(buf, *word_spans(buf, bounds)[:2])
        firsts = np.searchsorted(starts, bounds)
        _, at, which = np.unique(word_hashes(buf, starts, ends, 5), return_index=True, return_inverse=True)
        if not spelled_alike(buf, starts, ends, at[which]).all():  # two words have one hash: told apart by their bytes
            number = {}
            which = np.array([number.setdefault(raw[a:b], len(number)) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)])
            at = np.unique(which, return_index=True)[1]
        ids = self._ids([raw[a:b] for a, b in zip(starts[at].tolist(), ends[at].tolist(), strict=True)])
        flat, n = np.frombuffer(b"".join(ids), "<u4"), np.fromiter(map(len, ids), np.int64, len(ids)) // 4
        count, place = n[which], (np.cumsum(n) - n)[which]
        upto = np.concatenate(([0], np.cumsum(count)))
        out = flat[np.repeat(place - upto[:-1], count) + np.arange(upto[-1])]
        cuts = upto[firsts]
        return [out[a:b].tobytes() + self.end for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]

    def _ids(self, words: list[bytes]) -> list[bytes]:
        """Ids of distinct words. Long words are not remembered."""
        if len(self.known) > REMEMBERED:
            self.known.clear()
        out = list(map(self.known.get, words))
        new = [k for k, v in enumerate(out) if v is None]
        ids = [e.ids for e in self.tokenizer.encode_batch_fast([words[k].decode() for k in new], add_special_tokens=False)]
        blob, at = np.fromiter(chain.from_iterable(ids), "<u4").tobytes(), 0
        for k, n in zip(new, map(len, ids), strict=True):
            out[k] = blob[at : at + 4 * n]
            at += 4 * n
            if len(words[k]) <= SHORT_WORD:
                self.known[words[k]] = out[k]
        return out


def _parted(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Words, with the signs that end them cut off as words of their own where that is safe."""
    if not len(starts):
        return starts, ends
    plain = np.maximum.accumulate(np.where(_SIGN[buf], -1, np.arange(len(buf))))
    body = plain[ends - 1] + 1
    last, before = buf[np.maximum(body - 1, 0)], buf[np.maximum(body - 2, 0)]
    safe = _ALNUM[last] | ((before == 0xC3) & (last != 0x97) & (last != 0xB7) & (body - 2 >= starts))
    cut = (body < ends) & (body > starts) & safe
    left = np.where(cut, body, ends)
    order = np.argsort(both := np.concatenate((starts, body[cut])), kind="stable")
    return both[order], np.concatenate((left, ends[cut]))[order]


_ENCODERS: dict[tuple, Encoder] = {}


def encoder(path: str, end_id: int) -> Encoder:
    """This worker's encoder; what it remembers serves later tasks too."""
    if (path, end_id) not in _ENCODERS:
        _ENCODERS[path, end_id] = Encoder(path, end_id)
    return _ENCODERS[path, end_id]


def pack(lengths: list[int], longest: int = SEQ_LEN, shortest: int = SHORTEST_TIER) -> list[list[tuple[int, int, int]]]:
    """Sequences, each a list of pieces (document, start, length). Every sequence's tokens are a power of two, `longest` at most."""
    done: list[list[tuple[int, int, int]]] = []
    pool: list[tuple[int, int, int]] = []  # fragments (length, document, start) in ascending order
    for doc, n in enumerate(lengths):
        done += [[(doc, at, longest)] for at in range(0, n - longest + 1, longest)]
        if rest := n % longest:
            pool.append((rest, doc, n - rest))
    pool.sort()
    tier = longest
    while pool:
        if pool[-1][0] <= tier // 2 and tier > shortest:
            tier //= 2  # no fragment of this tier is left
            continue
        gap, row = tier, []
        while gap and pool:
            # the longest fragment that fits; the window's first is the tier's own
            at = bisect.bisect_right(pool, (gap, len(lengths), 0)) - 1
            if at >= 0:
                n, doc, start = pool.pop(at)
                row.append((doc, start, n))
            else:
                n, doc, start = pool.pop(0)
                row.append((doc, start, gap))
                bisect.insort(pool, (n - gap, doc, start + gap))
                n = gap
            gap -= n
        done += _exact(row) if gap else [row]
    return done


def _exact(row: list[tuple[int, int, int]]) -> list[list[tuple[int, int, int]]]:
    """A short row as sequences of powers of two."""
    out, total = [], sum(n for _, _, n in row)
    while total:
        want, seq = 1 << (total.bit_length() - 1), []
        total -= want
        while want:
            doc, start, n = row.pop(0)
            if n > want:
                row.insert(0, (doc, start + want, n - want))
                n = want
            seq.append((doc, start, n))
            want -= n
        out.append(seq)
    return out


def pack_documents(docs: DataFrame, vocabulary: str, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text", seq_len: int = SEQ_LEN) -> DataFrame:
    """One row for each piece: id, start, length, ids (32-bit little-endian), doc_tokens, sequence_id, offset, tier (window size) and step (group of STEP_TOKENS)."""
    rows = docs.select(F.col(f"`{id_col}`"), F.col(f"`{text_col}`"))
    schema = _PIECE.format(name=f"`{id_col}`", kind=dict(rows.dtypes)[id_col])
    names = [id_col, "start", "length", "ids", "doc_tokens", "sequence_id", "offset", "tier", "step"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part = encoder(vocabulary, end_id), TaskContext.get().partitionId() << 40
        held: list[tuple[object, bytes]] = []
        tokens = n_seq = n_step = 0
        kinds: list[pa.DataType] = []

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal n_seq, n_step
            cols: list[list] = [[] for _ in names]
            filled = size = 0
            for seq in sorted(pack([len(b) // 4 for _, b in held], seq_len), key=lambda s: -sum(p[2] for p in s)):
                total, offset = sum(p[2] for p in seq), 0
                for doc, start, n in seq:
                    key, ids = held[doc]
                    for c, v in zip(cols, (key, start, n, ids[4 * start : 4 * (start + n)], len(ids) // 4, part + n_seq, offset, total, part + n_step), strict=True):
                        c.append(v)
                    offset += n
                    size += n
                n_seq += 1
                filled += total
                if filled >= STEP_TOKENS:  # sizes are descending powers of two, so a step is met exactly
                    filled, n_step = 0, n_step + 1
                if size >= 1 << 20:
                    yield batch(cols)
                    cols, size = [[] for _ in names], 0
            if cols[0]:
                yield batch(cols)
            n_step += 1

        def batch(cols: list[list]) -> pa.RecordBatch:
            types = [kinds[0], pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)

        for b in batches:
            kinds = [b.schema.field(0).type]
            for at in range(0, b.num_rows, TEXTS):
                for key, ids in zip(b.column(0).slice(at, TEXTS).to_pylist(), encode(b.column(1).slice(at, TEXTS).to_pylist()), strict=True):
                    held.append((key, ids))
                    tokens += len(ids) // 4
                    if tokens >= GROUP_TOKENS:
                        yield from flush()
                        held, tokens = [], 0
        if held:
            yield from flush()

    return rows.mapInArrow(run, schema)
