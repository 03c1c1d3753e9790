"""Toxicity by a support vector machine on a subsequence string kernel, with Nyström landmarks.

A word is mapped to its subsequences of three letters (its beginning counts as one), each weighted down by the length it is spread over, so inserted characters and gaps
cost a little instead of all; punctuation inside a word is passed over, and letters set apart by blanks are read as a word. Two words' kernel is the inner product of
these, scaled by length, to the power POWER. A text is read in windows of WINDOW words; two windows' kernel is the sum over all pairs of their words. Sums, products and
scalings of inner products are inner products, so the kernel is positive definite.

Landmarks are windows of labelled texts, toxic and other. The machine is a linear one with squared hinge loss on their Nyström features. Labels are of texts, so it is
fitted in rounds: a toxic text stands for its highest windows, at first by the words that tell toxic texts from others, and all windows of other texts are wrong, of which
the highest are kept; toxic windows are also shown with characters put in or doubled. A text's score is that of its highest window, through a sigmoid whose middle leaves
nearly all labelled clean texts (ALLOWED) below it.

Fitting uses labelled rows up to MAX_POSITIVE and MAX_NEGATIVE, those with the smallest hashes of ids (words of over LONG bytes are not learned from); scoring reads every
whole text. Null or empty text: the score of a text without any near word. Without labelled rows of both kinds, or without a telling word, every score is the share of
toxic rows (0 without any). Repeated rows are scored alike; an empty table gives an empty result. Other columns do not matter.
"""

from __future__ import annotations

import random
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable

MAX_POSITIVE, MAX_NEGATIVE, TELLING, LONG = 3000, 6000, 4000, 200
#: Words of a window; windows that a toxic text stands for, at most; landmarks from toxic and from other texts, and how alike (to POWER 1) two may be.
WINDOW, STANDING, TOXIC_LANDMARKS, OTHER_LANDMARKS, ALIKE = 1, 3, 64, 32, 0.8
#: Rounds of fitting; disguised copies of a toxic window; weight of errors; share of labelled clean texts that may score over one half.
ROUNDS, DISGUISED, COST, ALLOWED = 2, 2, 20.0, 0.001
#: Weight of each place that a subsequence spreads over; most places; power of the kernel of words.
DECAY, SPREAD, POWER = 0.7, 7, 3
REMEMBERED, AT_ONCE = 400_000, 20_000

_GAPS = [(i, k) for k in range(2, SPREAD) for i in range(1, k)]  # second and third letter's distance from the first
_LEET = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a"}
_CODES = 1 << 18


def _codes() -> np.ndarray:
    """1 to 62 for letters and digits below U+3000; 63 for the beginning of a word; 0 for what is passed over."""
    out = np.zeros(0x3000, np.int64)
    for cp in range(0x3000):
        c = _LEET.get(chr(cp), chr(cp))
        out[cp] = ord(c) - 96 if "a" <= c <= "z" else 27 + cp % 36 if c.isalnum() else 0
    out[10] = 63
    return out


_CODE = _codes()


def tokens(text: str | None) -> list[bytes]:
    """A text's words in lower case, in order; a run of four or more single characters is one word."""
    words = (text or "").lower().encode().split()
    if sum(len(w) == 1 for w in words) < 4:
        return words
    out: list[bytes] = []
    run: list[bytes] = []
    for w in [*words, b"  "]:
        if len(w) == 1:
            run.append(w)
            continue
        out += [b"".join(run)] if len(run) >= 4 else run
        run = []
        out.append(w)
    return out[:-1]


def _triples(words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word number, code and weight of every subsequence of three letters within SPREAD places; a word's squared weights add up to 1."""
    # a line feed before each word stands for its beginning, and is a letter too
    cp = np.frombuffer(b"".join(b"\n" + w for w in words).decode(errors="replace").encode("utf-32-le", errors="replace"), np.uint32).astype(np.int64)
    word = np.cumsum(cp == 10) - 1
    code = np.where(cp < 0x3000, _CODE[np.minimum(cp, 0x2FFF)], 27 + cp % 36)
    keep = code > 0
    code, word = code[keep], word[keep]
    letters = np.bincount(word, minlength=len(words))
    scale = 1 / np.sqrt(np.maximum(sum(np.maximum(letters - k, 0) * DECAY ** (2 * k + 2) for _, k in _GAPS), DECAY**6))
    parts = []
    for i, k in _GAPS:
        if len(code) > k:
            same = np.flatnonzero(word[k:] == word[:-k])
            parts.append((word[same], (code[same] << 12) | (code[same + i] << 6) | code[same + k], scale[word[same]] * DECAY ** (k + 1)))
    return tuple(np.concatenate([p[c] for p in parts]) if parts else np.empty(0, kind) for c, kind in enumerate((np.int64, np.int64, float)))


class Kernel:
    """The kernel of any words with given ones."""

    def __init__(self, marks: list[bytes]) -> None:
        word, code, weight = _triples(marks)
        known, at = np.unique(code, return_inverse=True)
        self.n, self.place = len(marks), np.full(_CODES, -1, np.int32)
        self.place[known] = np.arange(len(known))
        self.table = np.zeros((len(known), self.n), np.float32)
        np.add.at(self.table, (at, word), weight)

    def __call__(self, words: list[bytes]) -> np.ndarray:
        word, code, weight = _triples(words)
        at = self.place[code]
        hit = np.flatnonzero(at >= 0)
        hit = hit[np.argsort(word[hit], kind="stable")]
        word, at, weight = word[hit], at[hit], weight[hit]
        out = np.zeros((len(words), self.n), np.float32)
        for lo in range(0, len(words), 512):
            i, j = np.searchsorted(word, (lo, lo + 512))
            rows = min(512, len(words) - lo)
            some = np.bincount((word[i:j] - lo) * len(self.table) + at[i:j], weights=weight[i:j], minlength=rows * len(self.table))
            out[lo : lo + rows] = some.astype(np.float32).reshape(rows, -1) @ self.table
        return out**POWER


def windows_kernel(windows: list[list[bytes]], marks: list[list[bytes]]) -> np.ndarray:
    """The kernel of windows: the sum over all pairs of their words."""
    first, of = _numbered(windows)
    second, to = _numbered(marks)
    k = Kernel([*second])([*first]).astype(float)
    cols = np.stack([k[:, ws].sum(axis=1) for ws in to], axis=1)
    return np.stack([cols[ws].sum(axis=0) for ws in of])


def _numbered(windows: list[list[bytes]]) -> tuple[dict[bytes, int], list[list[int]]]:
    number: dict[bytes, int] = {}
    return number, [[number.setdefault(w, len(number)) for w in ws] for ws in windows]


@dataclass
class Model:
    """A fitted machine: landmarks, their weights in a decision, offset, and calibration."""

    landmarks: list[list[bytes]]
    weights: np.ndarray
    offset: float
    slope: float = 1.0
    base: float = 0.0

    def worth(self) -> Callable[[list[bytes]], np.ndarray]:
        """Each word's share of a decision, as a function: the landmarks' words with all their weights."""
        number, of = _numbered(self.landmarks)
        share = np.zeros(len(number))
        for ws, weight in zip(of, self.weights, strict=True):
            np.add.at(share, ws, weight)
        kernel, share = Kernel([*number]), share.astype(np.float32)
        return lambda words: kernel(words) @ share

    def scores(self, decisions: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * (decisions + self.offset) + self.base, -40, 40)))


def sums(values: np.ndarray) -> np.ndarray:
    """Of all windows of WINDOW neighbours (one, if there are fewer)."""
    if len(values) <= WINDOW:
        return values.sum(keepdims=True)
    total = np.concatenate(([0.0], np.cumsum(values)))
    return total[WINDOW:] - total[:-WINDOW]


class Reader:
    """Values of a text's words, in order; those of words met before are remembered, within bounds."""

    def __init__(self, worth: Callable[[list[bytes]], np.ndarray]) -> None:
        self.worth, self.known = worth, {}

    def __call__(self, texts: list[str | None]) -> list[tuple[list[bytes], np.ndarray]]:
        if len(self.known) > REMEMBERED:
            self.known.clear()
        read = [tokens(t) for t in texts]
        new = list({w for ws in read for w in ws}.difference(self.known))
        for at in range(0, len(new), AT_ONCE):
            some = new[at : at + AT_ONCE]
            self.known.update(zip(some, self.worth(some).tolist(), strict=True))
        return [(ws, np.fromiter(map(self.known.__getitem__, ws), float, len(ws))) for ws in read]


def _texts_of(b: pa.RecordBatch, column: int, most: int = 256) -> Iterator[tuple[int, list[str | None]]]:
    for at in range(0, b.num_rows, most):
        yield at, b.column(column).slice(at, most).to_pylist()


def telling_words(sample: DataFrame, n_toxic: int, n_other: int) -> dict[bytes, float]:
    """Words that set toxic texts apart, TELLING at most, with the share of toxic texts that hold them less that of others. sample: text, toxic."""

    def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ys = b.column(1).to_pylist()
            for at, texts in _texts_of(b, 0):
                sets = [{w for w in tokens(t) if len(w) <= LONG} for t in texts]
                yield pa.RecordBatch.from_arrays([pa.array([w for s in sets for w in s], pa.binary()), pa.array([ys[at + k] for k, s in enumerate(sets) for _ in s], pa.int32())], ["word", "toxic"])

    counts = sample.select("text", "toxic").mapInArrow(words, "word binary, toxic int").groupBy("word").agg(F.sum("toxic").alias("p"), F.sum(1 - F.col("toxic")).alias("n"))
    lead = F.col("p") / n_toxic - F.col("n") / n_other
    telling = counts.where((F.length("word") >= 4) & (F.col("p") >= 2) & (F.col("p") / n_toxic > 4 * F.col("n") / n_other)).withColumn("lead", lead)
    return {bytes(r.word): r.lead for r in telling.orderBy(F.col("lead").desc(), "word").limit(TELLING).collect()}


def top_windows(sample: DataFrame, worth: Callable[[], Callable[[list[bytes]], np.ndarray]], others: int) -> list[tuple[int, bool, float, bytes]]:
    """For each row of sample (text, toxic), of its distinct windows: toxic, whether it is the first of the row, value and words of the highest; if toxic, also of the next
    ones of at least half its value; if not, of `others` more at random places."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read = Reader(worth())
        for b in batches:
            ys, out = b.column(1).to_pylist(), []
            for at, texts in _texts_of(b, 0):
                for k, (words, values) in enumerate(read(texts)):
                    fits = np.array([len(w) <= LONG for w in words], bool)
                    total = sums(np.where(fits, values, 0.0)) if words else np.zeros(1)
                    chance = random.Random(len(words) * 1_000_003 + sum(map(len, words)))
                    places = np.argsort(-total, kind="stable")[: 16 * STANDING].tolist() if ys[at + k] else [int(total.argmax()), *(chance.randrange(len(total)) for _ in range(others))]
                    seen: set[bytes] = set()
                    for place in places:
                        some = b" ".join(w for w in words[place : place + WINDOW] if len(w) <= LONG)
                        if some in seen or len(seen) >= max(STANDING, 1 + others) or (ys[at + k] and seen and total[place] < total[places[0]] / 2):
                            continue
                        out.append((ys[at + k], not seen, float(total[place]), some))
                        seen.add(some)
            cols = list(zip(*out, strict=True)) if out else [(), (), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int32(), pa.bool_(), pa.float64(), pa.binary()), strict=True)], ["toxic", "first", "value", "words"])

    # a few short rows for each row of the sample
    return [(r.toxic, r.first, r.value, bytes(r.words)) for r in sample.select("text", "toxic").mapInArrow(run, "toxic int, first boolean, value double, words binary").collect()]


def disguise(word: bytes, chance: random.Random) -> bytes:
    """A word with one or two characters put in, or one doubled."""
    letters = list(word.decode(errors="replace"))
    kind = chance.randrange(4)
    for _ in range(2 if kind == 0 else 1):
        at = chance.randrange(1, max(2, len(letters)))
        letters.insert(at, chance.choice("abcdefghijklmnopqrstuvwxyz") if kind <= 2 else letters[at - 1])
    return "".join(letters).encode()


def choose_landmarks(windows: list[bytes], most: int) -> list[list[bytes]]:
    """The first of the windows that are not much like any before."""
    chosen: list[list[bytes]] = []
    for at in range(0, len(windows), 64):
        some = [ws for w in windows[at : at + 64] if (ws := w.split())]
        if not some or len(chosen) == most:
            continue
        near = windows_kernel(some, chosen + some)
        kept = list(range(len(chosen)))
        for k, ws in enumerate(some):
            if len(kept) < most and (not kept or near[k, kept].max() < ALIKE**POWER * len(ws) ** 2):
                kept.append(len(chosen) + k)
        chosen = [(chosen + some)[k] for k in kept]
    return chosen


def fit_machine(windows: list[list[bytes]], y: np.ndarray, landmarks: list[list[bytes]], cost: float = COST) -> Model:
    """A linear machine on Nyström features of windows, by Newton steps on squared hinge loss."""
    between = windows_kernel(landmarks, landmarks)
    value, vector = np.linalg.eigh((between + between.T) / 2)
    root = (vector / np.sqrt(np.maximum(value, 1e-3))) @ vector.T
    x = np.hstack((windows_kernel(windows, landmarks) @ root, np.ones((len(windows), 1))))
    t = np.where(y > 0, 1.0, -1.0)
    w, ridge = np.zeros(x.shape[1]), np.ones(x.shape[1])
    ridge[-1] = 1e-3
    for step in range(60):
        on = t * (x @ w) < 1
        new = np.linalg.solve(cost * x[on].T @ x[on] + np.diag(ridge), cost * x[on].T @ t[on])
        if np.abs(new - w).max() < 1e-9:
            break
        w = 0.5 * w + 0.5 * new if step > 20 else new
    return Model(landmarks, root @ w[:-1], float(w[-1]))


def calibrate(model: Model, f: np.ndarray, y: np.ndarray) -> None:
    """A sigmoid on decisions: its middle leaves all but ALLOWED of the clean ones below, but not more than a tenth of the toxic ones; its slope suits both kinds alike."""
    f = f + model.offset
    middle = max(0.0, min(float(np.quantile(f[y == 0], 1 - ALLOWED)), float(np.quantile(f[y == 1], 0.1))))
    f, c = f - middle, np.where(y > 0, len(y) / max(1, y.sum()), len(y) / max(1, (1 - y).sum())) / 2
    goal = np.where(y > 0, (y.sum() + 1) / (y.sum() + 2), 1 / ((1 - y).sum() + 2))
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(model.slope * f, -40, 40)))
        h, g = c * np.maximum(p * (1 - p), 1e-9), c * (p - goal)
        model.slope = float(np.clip(model.slope - np.clip((g * f).sum() / ((h * f * f).sum() + 1e-6), -2, 2), 0.1, 50.0))
    model.base = -model.slope * middle


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> Model | float:
    """A model from labelled rows (labels: id and 0 or 1), or the share of toxic ones if there is nothing to learn from."""
    given = labels.select(F.col(f"`{id_col}`").alias("l"), F.col(f"`{label_col}`").cast("int").alias("toxic")).where("l IS NOT NULL AND toxic IN (0, 1)")
    order = [F.xxhash64("l"), "l"]
    chosen = given.where("toxic = 1").orderBy(*order).limit(MAX_POSITIVE).unionByName(given.where("toxic = 0").orderBy(*order).limit(MAX_NEGATIVE))
    # at most MAX_POSITIVE + MAX_NEGATIVE rows, so small enough to broadcast
    sample = durable(docs.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text_col}`").alias("text")).join(F.broadcast(chosen), F.col("id") == F.col("l")).select("text", "toxic"))
    n, n_toxic = sample.agg(F.count(F.lit(1)), F.coalesce(F.sum("toxic"), F.lit(0))).first()
    lead = telling_words(sample, n_toxic, n - n_toxic) if 0 < n_toxic < n else {}
    if not lead:
        return n_toxic / n if n else 0.0

    worth = lambda: lambda words: np.array([lead.get(w, 0.0) for w in words])
    found = top_windows(sample, worth, 2)
    chance, wrong = random.Random(7), set()
    toxic, hard = [w for y, _, v, w in found if y == 1 and v > 0], []
    for step in range(ROUNDS):
        value = worth()
        wrong |= {w for y, _, _, w in found if y == 0 and w}
        hard = sorted((w for w in wrong), key=lambda w: chance.random()) if step == 0 else hard
        often, right, odd = Counter(toxic), [], []
        for w, n in sorted(often.items()):
            words = w.split()
            at = int(np.argmax(value(words)))  # the word that tells most is disguised
            right += [words] * n
            odd += [[*words[:at], disguise(words[at], chance), *words[at + 1 :]] for _ in range(DISGUISED * n)]
        landmarks = choose_landmarks(sorted(often, key=lambda w: (-often[w], w)), TOXIC_LANDMARKS) + choose_landmarks(hard[: 8 * OTHER_LANDMARKS], OTHER_LANDMARKS)
        model = fit_machine(right + odd + [w.split() for w in sorted(wrong)], np.repeat([1, 0], [len(right) + len(odd), len(wrong)]), landmarks)
        worth = model.worth
        found = top_windows(sample, worth, 0)
        toxic = [w for y, _, v, w in found if y == 1 and v + model.offset > -0.5 and w] or toxic
        hard = [w for _, w in sorted({(-v, w) for y, _, v, w in found if y == 0 and w})]
    first = [(v, y) for y, one, v, _ in found if one]
    calibrate(model, np.array([v for v, _ in first]), np.array([y for _, y in first]))
    return model


def score(docs: DataFrame, model: Model | float, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and score for each row."""
    rows = docs.select(F.col(f"`{id_col}`"), F.col(f"`{text_col}`"))
    if isinstance(model, float):
        return rows.select(F.col(f"`{id_col}`"), F.lit(model).alias("score"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read = Reader(model.worth())
        for b in batches:
            for at, texts in _texts_of(b, 1):
                best = np.array([sums(values).max() for _, values in read(texts)])
                yield pa.RecordBatch.from_arrays([b.column(0).slice(at, len(texts)), pa.array(model.scores(best))], [id_col, "score"])

    return rows.mapInArrow(run, f"`{id_col}` {dict(rows.dtypes)[id_col]}, score double")
