"""Toxicity by a subsequence string-kernel support vector machine with Nystroem landmarks.

The kernel of two words counts their common subsequences of three letters, each weighted by a decay
for every letter it skips, so a word with gaps or inserted characters stays close to itself: signs,
digits and marks match nothing and only widen the gap. Letters are compared without case and
accents. A text is the set of its words (and of its runs of single letters, read as one word); its
value is that of its worst word. Landmark words give the Nystroem map; the machine is trained on
the worst word of each toxic text against the worst words of clean ones, chosen again each round,
and calibrated on texts that it has not seen, fold by fold.
Since the map is linear in the kernel, the machine folds into one weight for each three letters,
and a word's value is a sum over its subsequences.
"""

from __future__ import annotations

import unicodedata
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from incwalk.llm.common import forget
from incwalk.llm.common import memo as new_memo

ORDER, SPAN, DECAY = 3, 6, 0.7
LETTERS = 27  # 0 is for what matches nothing
LONGEST = 24
LANDMARKS = 160
#: Labelled texts of each kind that are learned from, at most; those of least hash are taken.
TOXIC_SAMPLE, CLEAN_SAMPLE = 1500, 3000
#: Longer texts, in UTF-8 bytes, aren't learned from, so the sample is bounded in bytes too. They are scored whole.
LONGEST_LEARNED = 256 << 10
MEMO = 500_000


def _code(c: str) -> int:
    base = unicodedata.normalize("NFD", c)[:1].lower()
    return ord(base) - 96 if "a" <= base <= "z" else 0


class _Codes(dict):
    def __missing__(self, c):
        self[c] = v = _code(c)
        return v


_CODES = _Codes()
_PLACES: dict[int, tuple] = {}


def _places(m: int):
    """Places and weights of all subsequences of a word of m letters within the span."""
    if m not in _PLACES:
        t = [(i, j, k) for i in range(m) for j in range(i + 1, min(m, i + SPAN)) for k in range(j + 1, min(m, i + SPAN))]
        a = np.array(t, np.int64).reshape(-1, 3)
        _PLACES[m] = (a, (DECAY ** (a[:, 2] - a[:, 0] - 2)).astype(np.float32))
    return _PLACES[m]


def windows(word: str) -> list[str]:
    """Long words as overlapping windows."""
    return [word] if len(word) <= LONGEST else [word[i : i + LONGEST] for i in range(0, len(word) - LONGEST // 2, LONGEST // 2)]


def subsequences(words: list[str]):
    """``(which words, features, weights, scales)`` by length of word; a word is scaled by what it holds of letters."""
    by: dict[int, list[int]] = {}
    for n, w in enumerate(words):
        by.setdefault(len(w), []).append(n)
    for m, own in by.items():
        if m < ORDER:
            continue
        at, weight = _places(m)
        for i in range(0, len(own), 4000):
            some = own[i : i + 4000]
            codes = np.array([[_CODES[c] for c in words[n]] for n in some], np.int64)
            a, b, c = (codes[:, at[:, k]] for k in range(3))
            f = np.where((a > 0) & (b > 0) & (c > 0), (a * LETTERS + b) * LETTERS + c, 0).astype(np.int16)
            yield np.array(some), f, weight, 1 / np.sqrt(np.maximum((f > 0) @ weight**2, 1e-3))


def dense(words: list[str]) -> np.ndarray:
    out = np.zeros((len(words), LETTERS**3), np.float32)
    for own, f, w, scale in subsequences(words):
        for n, row, by in zip(own, f, scale, strict=True):
            np.add.at(out[n], row, w * by)
    out[:, 0] = 0
    return out


@dataclass
class Model:
    weight: np.ndarray
    bias: float
    slope: float
    shift: float
    floor: float = 0.0  # how many texts are labelled toxic whatever their words

    @property
    def wordless(self) -> float:
        """The value of a text without words: on the clean side of the margin."""
        return min(-1.0, self.bias)

    def values(self, words: list[str]) -> np.ndarray:
        return self.values_of(len(words), subsequences(words))

    def values_of(self, n: int, found) -> np.ndarray:
        out = np.full(n, self.bias, np.float32)
        for own, f, w, scale in found:
            out[own] += (self.weight[f] @ w) * scale
        return out

    def probability(self, value):
        return self.floor + (1 - self.floor) / (1 + np.exp(-np.clip(self.slope * value + self.shift, -60, 60)))


def instances(text: str | None) -> list[str]:
    """Words of a text, and every run of three or more single characters as one word; long ones as windows."""
    words = text.lower().split() if text else []
    if not words:
        return []
    out = [p for w in words if len(w) > LONGEST for p in windows(w)]
    single = [len(w) == 1 for w in words]
    if sum(single) >= 3:
        run = []
        for w, one in zip([*words, ""], [*single, False], strict=True):
            if one:
                run.append(w)
            else:
                if len(run) >= 3:
                    out += windows("".join(run))
                run = []
    return [w for w in words if len(w) <= LONGEST] + out if out else words


def _machine(z: np.ndarray, y: np.ndarray, cost: float = 30.0) -> np.ndarray:
    """Linear machine with squared hinge loss and a free bias in the last place, by Newton steps on the active rows."""
    x = np.c_[z, np.ones(len(z))]
    c = np.where(y > 0, cost * max(1.0, (y < 0).sum() / max(1, (y > 0).sum())), cost)
    ridge = np.r_[np.ones(z.shape[1]), 1e-6]
    v = np.zeros(x.shape[1])

    def loss(v):
        return (ridge * v * v).sum() / 2 + (c * np.maximum(0, 1 - y * (x @ v)) ** 2).sum()

    for _ in range(60):
        slack = 1 - y * (x @ v)
        on = slack > 0
        xo = x[on]
        g = ridge * v - 2 * xo.T @ (c[on] * y[on] * slack[on])
        h = np.diag(ridge) + 2 * (xo * c[on][:, None]).T @ xo
        d = np.linalg.solve(h, g)
        step, before = 1.0, loss(v)
        while step > 1e-6 and loss(v - step * d) > before - 1e-4 * step * (g @ d):
            step /= 2
        v = v - step * d
        if before - loss(v) < 1e-6 * before:
            break
    return v


def _calibrate(s: np.ndarray, y: np.ndarray) -> tuple[float, float, float]:
    """Slope, shift and floor of ``floor + (1 - floor) * logistic``, by Newton steps for slope and shift at each of a grid of floors; the likeliest floor wins."""
    n1, n0 = (y > 0).sum(), (y < 0).sum()
    t = np.where(y > 0, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    x, best = np.c_[s, np.ones(len(s))], None
    for floor in (n1 / len(y)) * np.array([0.0, 0.05, 0.1, 0.2, 0.3, 0.4, 0.5, 0.7]):
        b, r = np.array([1.0, 0.0]), t
        for _ in range(30):  # a label comes from the floor or from the words: shares by the curve so far, then the curve by the shares
            p = 1 / (1 + np.exp(-np.clip(x @ b, -60, 60)))
            r = t * p / np.maximum(floor + (1 - floor) * p, 1e-12)
            for _ in range(5):
                p = 1 / (1 + np.exp(-np.clip(x @ b, -60, 60)))
                h = (x * (p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(2)
                step = np.linalg.solve(h, x.T @ (r - p) - 1e-3 * b)
                b = b + step * min(1.0, 4 / max(1e-9, np.abs(step).max()))
        p = np.clip(floor + (1 - floor) / (1 + np.exp(-np.clip(x @ b, -60, 60))), 1e-9, 1 - 1e-9)
        fit = (t * np.log(p) + (1 - t) * np.log(1 - p)).sum()
        if best is None or fit > best[0]:
            best = fit, float(b[0]), float(b[1]), float(floor)
    return best[1:]


def _cover(bags: list[np.ndarray], odds: np.ndarray, toxic: np.ndarray, most: int) -> tuple[list[int], list[int]]:
    """Words that explain the toxic texts, greedily: each next one has the most odds over texts not explained twice. And the first such word of each text."""
    left = np.where(toxic, 2, 0)
    holds: dict[int, list[int]] = {}
    for k in np.flatnonzero(toxic):
        for n in bags[k]:
            if odds[n] > 0.5:
                holds.setdefault(int(n), []).append(int(k))
    score = {n: odds[n] * sum(left[k] for k in own) for n, own in holds.items()}
    first, out = [-1] * len(bags), []
    while score and len(out) < most:
        n = max(score, key=lambda m: (score[m], -m))
        if score[n] <= 0:
            break
        out.append(n)
        for k in holds[n]:
            if first[k] < 0:
                first[k] = n
            if left[k]:
                left[k] -= 1
                for m in bags[k]:
                    if int(m) in score:
                        score[int(m)] -= odds[m]
        del score[n]
    return out, first


def _fit(own: list[np.ndarray], words: list[str], found: list, y: np.ndarray, fit: np.ndarray, rounds: int, seed: int) -> Model:
    """A machine without calibration, learned from the texts that ``fit`` marks.

    The first positives are the words that explain toxic texts best; later ones are the worst words
    under the machine so far. A toxic text whose worst word stays on the clean side counts as
    unexplained and is left out of that round, so that labels without an insult teach nothing.
    """
    rng = np.random.default_rng(seed)
    none = Model(np.zeros(LETTERS**3, np.float32), 0.0, 0.0, -8.0)
    n1, n0 = np.zeros(len(words)), np.zeros(len(words))
    for k in np.flatnonzero(fit):
        (n1 if y[k] > 0 else n0)[own[k]] += 1
    odds = np.log((n1 + 0.5) / ((y[fit] > 0).sum() + 1)) - np.log((n0 + 0.5) / ((y[fit] < 0).sum() + 1))
    odds[(n1 < 2) | (np.array([len(w) for w in words]) < ORDER)] = -9
    marks, worst = _cover(own, odds, fit & (y > 0), LANDMARKS * 3 // 4)
    marks = [words[n] for n in marks]
    common = [n for n in range(len(words)) if n0[n] >= 1 and len(words[n]) >= ORDER]
    marks += [words[n] for n in rng.choice(common, min(len(common), LANDMARKS - len(marks)), replace=False)] if common else []
    if not marks:
        return none
    phi = dense(marks).astype(np.float64)
    vals, vecs = np.linalg.eigh(phi @ phi.T)
    root = vecs / np.sqrt(np.maximum(vals, 1e-3 * vals.max()))
    to_map = phi.T @ root  # three letters to Nystroem coordinates
    to_map[0] = 0
    model, known = None, {}

    def coordinates(which):
        new = [n for n in which if n not in known]
        for some, f, w, scale in subsequences([words[n] for n in new]):
            for i, row, by in zip(some, f, scale, strict=True):
                known[new[i]] = (w @ to_map[row]) * by
        return np.array([known.get(n, nothing) for n in which])

    nothing = np.zeros(to_map.shape[1])
    negatives: set[int] = {int(n) for k in range(len(own)) if fit[k] and y[k] < 0 and len(own[k]) for n in rng.choice(own[k], min(2, len(own[k])), replace=False)}
    value = None
    for _ in range(rounds):
        if model is not None:
            value = model.values_of(len(words), found)
            worst = [int(ids[np.argmax(value[ids])]) if len(ids) else -1 for ids in own]
        pos = [worst[k] for k in range(len(own)) if fit[k] and y[k] > 0 and worst[k] >= 0 and (value is None or value[worst[k]] > 0)]
        negatives |= {worst[k] for k in range(len(own)) if fit[k] and y[k] < 0 and worst[k] >= 0}
        if not pos:
            break
        neg = sorted(negatives)
        v = _machine(coordinates(pos + neg), np.array([1.0] * len(pos) + [-1.0] * len(neg)))
        model = Model((to_map @ v[:-1]).astype(np.float32), float(v[-1]), 1.0, 0.0)
    return model or none


def train(texts: list[str], toxic: list[bool], rounds: int = 8, seed: int = 7, folds: int = 3) -> Model:
    """A machine learned from all texts and calibrated on values that each text gets from a machine that has not seen it.

    Without two texts of each kind, a model that calls nothing toxic.
    """
    bags = [sorted(set(instances(t))) for t in texts]
    y = np.array([1 if t else -1 for t in toxic])
    if (y > 0).sum() < 2 or (y < 0).sum() < 2:
        return Model(np.zeros(LETTERS**3, np.float32), 0.0, 0.0, -8.0)
    vocabulary = {w: n for n, w in enumerate(sorted({w for b in bags for w in b}))}
    words = list(vocabulary)
    own = [np.array([vocabulary[w] for w in b], np.int64) for b in bags]
    found = list(subsequences(words))
    fold = np.zeros(len(y), np.int64)
    for kind in (1, -1):
        fold[y == kind] = np.arange((y == kind).sum()) % folds

    def worst(model, which):
        value = model.values_of(len(words), found)
        return [value[own[k]].max() if len(own[k]) else model.wordless for k in np.flatnonzero(which)]

    s = np.zeros(len(y))
    for f in range(folds):
        s[fold == f] = worst(_fit(own, words, found, y, fold != f, rounds, seed), fold == f)
    model = _fit(own, words, found, y, np.ones(len(y), bool), rounds, seed)
    model.slope, model.shift, model.floor = _calibrate(s, y)
    return model


def labelled_texts(docs: DataFrame, labels: DataFrame, label_col: str = "toxic", toxic: int = TOXIC_SAMPLE, clean: int = CLEAN_SAMPLE) -> tuple[list[str], list[bool]]:
    """A bounded sample of labelled texts, for the driver: ids of least hash, picked by a broadcast of that bound."""
    ids = labels.where(F.col("doc_id").isNotNull() & F.col(label_col).isNotNull() & (F.crc32(F.col("doc_id").cast("string")) % 4 != 2)).groupBy("doc_id").agg(F.max(label_col).alias("y"))
    order = (F.xxhash64("doc_id"), F.col("doc_id"))
    some = ids.where("y = 1").orderBy(*order).limit(toxic).union(ids.where("y = 0").orderBy(*order).limit(clean))
    texts = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    got = texts.where(F.coalesce(F.octet_length("text"), F.lit(0)) <= LONGEST_LEARNED).join(F.broadcast(some), "doc_id").select("doc_id", "text", "y").collect()
    got.sort(key=lambda r: (hash_order(r["doc_id"]), r["text"] or ""))
    return [r["text"] or "" for r in got], [r["y"] == 1 for r in got]


def hash_order(n: int) -> int:
    return (n * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF) >> 7


_MEMOS: dict = {}  # by model, the words' values of the last one


def score_texts(docs: DataFrame, model: Model, threshold: float = 0.3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id``, ``held_out``, ``score`` and ``predicted`` of every row.

    Whole texts; null and empty ones get the score of a text without any word that speaks for label
    1. Repeated rows and null ids give a row each (a null id isn't held out); other columns are not read.
    """
    schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32())])
    key = hash((model.weight.tobytes(), model.bias))

    def run(batches):
        if key not in _MEMOS:
            forget()
            _MEMOS.clear()
            _MEMOS[key] = new_memo()
        memo = _MEMOS[key]
        for batch in batches:
            texts = batch.column("text")
            value = np.full(len(texts), model.wordless)
            for i in range(0, len(texts), 300):
                bags = [instances(t.as_py()) for t in texts[i : i + 300]]
                if len(memo) > MEMO:
                    memo.clear()
                new = list({w for b in bags for w in b if w not in memo})
                memo.update(zip(new, model.values(new).tolist(), strict=True))
                get = memo.__getitem__
                for k, b in enumerate(bags):
                    if b:
                        value[i + k] = max(map(get, b))
            p = model.probability(value)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(p), pa.array((p >= threshold).astype(np.int32))], schema=schema)

    held = F.coalesce(F.crc32(F.col(id_col).cast("string")) % 4 == 2, F.lit(False))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), held.alias("held_out"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")
