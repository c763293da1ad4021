"""Toxicity by a subsequence string-kernel support vector machine with Nyström landmarks.

The kernel of two strings sums, over the subsequences of three characters that both have, a decay to the power of
the stretch that each covers, and is divided by the roots of both strings' kernels with themselves; gaps and inserted
characters weaken a match and don't break it. Landmarks are units of labelled training texts, toxic and clean ones. The
same kernel gives a unit's products with the landmarks and the landmarks' own matrix, whose inverse root turns the
products into Nyström coordinates. On these a linear machine with squared hinge loss is trained. A text is toxic for one
of its units, so a toxic text trains with the unit that the machine finds most toxic, found anew between rounds
(multiple-instance training), a clean one with all. A text's margin is its highest unit's; a logistic curve turns margins
into probabilities at the labels' own rate.

What is learned comes down to a weight for every landmark, and, as a kernel is a sum over subsequences, to a weight for
every subsequence of three: a unit's margin is summed from these, exactly, without a visit to each landmark.

Units are runs of non-blank characters, lower-cased and without outer punctuation; runs of lone characters are also
read as one unit; long units are read in overlapping windows, so whole texts count.

Null and empty texts get the score of a text without any match. Repeated rows are judged alike; null ids and other
columns need no care; an empty table gives an empty result. Without labels of both kinds every score is the rate of
toxic labels (0 without labels). Training takes a bounded sample: ``SAMPLE`` labelled rows of either kind by a hash of
the id, and of a text with more distinct units than ``BAG_UNITS`` so many by a hash of them, from all over the text.
"""

from __future__ import annotations

import hashlib
import heapq
import re
import zlib
from collections import Counter
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from slicegrad.llm.common import process_cache, ship_by_value

ship_by_value(__name__)

SAMPLE = 2_500
BAG_UNITS = 4_000
LANDMARKS = 400
#: Clean units that a machine is trained against.
CLEAN_UNITS = 4_000
DECAY = 0.8
ORDER = 3
WINDOW = 12
#: Units that speak for a text.
TOP = 3
#: Part of the highest margin that makes another unit a witness too.
NEAR = 0.4
CACHED = 300_000
#: Stands before every unit, so that a unit's start counts as a character.
START = "^"
EDGES = ".,;:!?\"'()[]{}|%&$#*<>=/\\-_+~`^@"


_SPACED_OUT = re.compile(r"(?<!\S)\S\s+\S\s+\S(?!\S)")


def units(text: str | None) -> set[str]:
    """The distinct units of a text."""
    words = (text or "").lower().split()
    out = {w.strip(EDGES) for w in set(words)}
    run: list[str] = []
    for w in (*words, "") if _SPACED_OUT.search(text or "") else ():
        if len(w) == 1:
            run.append(w)
        elif run:
            if len(run) > 2:
                out.add("".join(run))
            run = []
    out.discard("")
    out = {START + w for w in out}
    long = [w for w in out if len(w) > WINDOW]
    for w in long:
        out.discard(w)
        out.update(w[k : k + WINDOW] for k in range(0, len(w) - WINDOW // 2, WINDOW // 2))
    return out


def codes(strings: list[str], width: int) -> np.ndarray:
    return np.array(strings, dtype=f"U{width}").view(np.uint32).reshape(len(strings), width)


def kernels(x: np.ndarray, y: np.ndarray, decay: float = DECAY, order: int = ORDER) -> np.ndarray:
    """Kernel, not yet divided, of row i of ``x`` with row i of ``y``, rows of character codes that end in zeros.

    ``open_[q][j]`` sums matched subsequences of length q that end before place j of ``y``, each weighed by the decay
    over what it covers so far of both strings. Places come first, so that every step is over all rows at once.
    """
    x, y = np.ascontiguousarray(x.T), np.ascontiguousarray(y.T)
    long, n = y.shape
    total = np.zeros(n)
    open_ = [np.ones((long, n))] + [np.zeros((long, n)) for _ in range(order - 1)]
    for c in x:
        if not c.any():
            break
        same = (y == c) & (c != 0)
        total += (same * open_[order - 1]).sum(0) * decay * decay
        for q in range(order - 1, 0, -1):
            fresh = same * open_[q - 1] * (decay * decay)
            along = np.zeros(n)
            for j in range(long):
                open_[q][j] *= decay
                open_[q][j] += along
                along = decay * along + fresh[j]
    return total


def by_length(words: list[str]) -> dict[int, np.ndarray]:
    """Length to the numbers of the words that have it."""
    size = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    return {int(n): np.flatnonzero(size == n) for n in np.unique(size)}


def own_kernels(words: list[str], rows: int = 4096) -> np.ndarray:
    """Roots of the words' kernels with themselves; 0 for words under three characters."""
    out = np.zeros(len(words))
    for n, own in by_length(words).items():
        for lo in range(0, len(own) if n >= ORDER else 0, rows):
            part = own[lo : lo + rows]
            c = codes([words[k] for k in part], n)
            out[part] = np.sqrt(kernels(c, c))
    return out


def triples(n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Places of every subsequence of three of ``n`` characters, and the decay over the stretch that it covers."""
    i, j, k = np.array(list(combinations(range(n), ORDER))).reshape(-1, ORDER).T
    return i, j, k, DECAY ** (k - i + 1.0)


class Alphabet:
    """Numbers for some characters, 0 for any other; a subsequence is one number."""

    def __init__(self, characters: str):
        self.known = np.unique(np.array(list(characters), dtype="U1").view(np.uint32)) if characters else np.zeros(0, dtype=np.uint32)
        self.size = len(self.known) + 1

    def subsequences(self, words: list[str], n: int):
        """Of words of length ``n``: the numbers (a row a word) and their decays."""
        c = codes(words, n)
        at = np.searchsorted(self.known, c).clip(max=max(len(self.known) - 1, 0))
        c = np.where(self.known[at] == c, at + 1, 0) if len(self.known) else np.zeros(c.shape, dtype=np.int64)
        i, j, k, decay = triples(n)
        whole = (c[:, i] != 0) & (c[:, j] != 0) & (c[:, k] != 0)
        return np.where(whole, (c[:, i] * self.size + c[:, j]) * self.size + c[:, k], 0), decay


def products(words: list[str], landmarks: list[str], block: int = 100) -> np.ndarray:
    """The kernel, divided, of every word with every landmark; a block of landmarks at a time, which bounds the memory."""
    parts = [_products(words, landmarks[k : k + block]) for k in range(0, len(landmarks), block)]
    left, right = own_kernels(words), own_kernels(landmarks)
    return np.concatenate(parts, axis=1) / np.maximum(left, 1e-300)[:, None] / np.maximum(right, 1e-300)


def _products(words: list[str], landmarks: list[str]) -> np.ndarray:
    alphabet = Alphabet("".join(landmarks))
    places: dict[int, int] = {}
    found = []
    for k, z in enumerate(landmarks):
        if len(z) >= ORDER:
            number, decay = alphabet.subsequences([z], len(z))
            found.append((k, [places.setdefault(s, len(places)) for s in number[0].tolist()], decay))
    marks = np.zeros((len(landmarks), len(places) + 1))
    for k, own, decay in found:
        np.add.at(marks[k], own, decay)
    column = np.full(alphabet.size**ORDER, len(places), dtype=np.int64)  # the last column takes what no landmark has
    column[list(places)] = list(places.values())
    column[0] = len(places)
    marks[:, -1] = 0
    out = np.zeros((len(words), len(landmarks)))
    for n, own in by_length(words).items():
        for lo in range(0, len(own) if n >= ORDER else 0, 128):
            part = own[lo : lo + 128]
            number, decay = alphabet.subsequences([words[k] for k in part], n)
            held = np.zeros((len(part), len(places) + 1))
            np.add.at(held, (np.arange(len(part))[:, None], column[number]), decay[None, :])
            out[part] = held @ marks.T
    return out


def subsequence_weights(landmarks: list[str], alpha: np.ndarray) -> tuple[str, np.ndarray]:
    """The characters, and the weight of every subsequence of three of them, which landmarks' weights come down to."""
    characters = "".join(sorted(set("".join(landmarks))))
    alphabet, own = Alphabet(characters), own_kernels(landmarks)
    out = np.zeros(alphabet.size**ORDER)
    for z, a, root in zip(landmarks, alpha, own):
        if len(z) >= ORDER:
            number, decay = alphabet.subsequences([z], len(z))
            np.add.at(out, number[0], a * decay / root)
    out[0] = 0
    return characters, out


class Scorer:
    """Margins of units, without the bias and 0 if below; those of frequent units are remembered."""

    def __init__(self, characters: str, weights: np.ndarray):
        self.alphabet, self.weights = Alphabet(characters), weights
        self.young: dict[str, float] = {}
        self.old: dict[str, float] = {}

    def margins(self, words: list[str]) -> np.ndarray:
        out = np.zeros(len(words))
        for n, own in by_length(words).items():
            if n < ORDER:
                continue
            rows = max(1, (1 << 20) // max(1, n * (n - 1) * (n - 2) // 6))
            for lo in range(0, len(own), rows):
                part = own[lo : lo + rows]
                number, decay = self.alphabet.subsequences([words[k] for k in part], n)
                out[part] = np.einsum("ij,j->i", self.weights[number], decay)
        out = np.maximum(out, 0.0)  # below 0, a unit is none that decides
        some = np.flatnonzero(out)
        out[some] /= own_kernels([words[k] for k in some])
        return out

    def texts(self, texts: list[str | None]) -> np.ndarray:
        """Of each text's units the highest margin, and the mean of the next two; 0 where none is above."""
        out = np.zeros((len(texts), 2))
        for at in range(0, len(texts), 128):  # so few texts' units are in memory at once
            self.settle([units(t) for t in texts[at : at + 128]], out[at : at + 128])
        return out

    def settle(self, bags: list[set[str]], out: np.ndarray) -> None:
        known: dict[str, float] = {}
        fresh = []
        young, old = self.young, self.old
        for word in set().union(*bags):
            v = young.get(word)
            if v is None:
                v = old.get(word)
                if v is None:
                    fresh.append(word)
                    continue
                young[word] = v
            known[word] = v
        if fresh:
            found = dict(zip(fresh, self.margins(fresh).tolist()))
            known |= found
            if len(young) >= CACHED // 2:
                self.old, self.young = young, {}
            self.young |= found
        for k, bag in enumerate(bags):
            out[k] = spoken(map(known.__getitem__, bag))


def pick_landmarks(toxic: list[set[str]], clean: list[set[str]], most: int = LANDMARKS) -> tuple[list[str], dict[str, float]]:
    """Units of the training texts, and how much each tells toxic texts apart (log odds).

    Toxic ones by how many texts they add to those that earlier ones are in, a text counting until five are in it, less
    the clean ones; then as many clean ones, half by how many texts have them and half by a hash.
    """
    in_toxic, in_clean = Counter(w for t in toxic for w in t), Counter(w for t in clean for w in t)
    a, b = len(toxic) + 1, len(clean) + 1
    odds = {w: float(np.log((n + 0.5) / a) - np.log((in_clean[w] + 0.5) / b)) for w, n in in_toxic.items()}
    least = max(2, len(toxic) // 400)
    ranked = sorted((w for w, n in in_toxic.items() if len(w) > ORDER and n >= least and odds[w] > 1), key=lambda w: (-in_toxic[w] * odds[w], w))[:2000]
    where: dict[str, list[int]] = {w: [] for w in ranked}
    for i, t in enumerate(toxic):
        for w in t & where.keys():
            where[w].append(i)
    covered, out = np.zeros(len(toxic)), []
    while ranked and len(out) < most // 2:
        gain = {w: (5 - covered[where[w]]).clip(0).sum() * odds[w] - 2 * in_clean[w] for w in ranked}
        best = max(ranked, key=lambda w: (gain[w], w))
        if gain[best] <= 0:
            break
        out.append(best)
        covered[where[best]] += 1
        ranked = [w for w in ranked if w != best and gain[w] > 0]
    rest = [w for w in in_clean if len(w) > ORDER and w not in set(out)]
    frequent = sorted(rest, key=lambda w: (-in_clean[w], w))[: most // 4]
    chosen = set(frequent)
    some = sorted((w for w in rest if w not in chosen), key=lambda w: (zlib.crc32(w.encode("utf-8", "surrogatepass")), w))[: most // 4]
    return out + frequent + some, odds


def broken_up(words: list[str]) -> list[str]:
    """The units with a character put between all others, put in, left out or put in another's place: what evasion looks like."""
    out = []
    for i, word in enumerate(words):
        x = word.removeprefix(START)
        mark, at = ".-*_ "[i % 4], 1 + i % max(1, len(x) - 1)
        out.append(START + (mark.join(x), x[:at] + mark + x[at:], x[:at] + x[at + 1 :], x[:at] + mark + x[at + 1 :])[i // 2 % 4])
    return out


def train_svm(x: np.ndarray, y: np.ndarray, sample_weight: np.ndarray, cost: float = 10.0, rounds: int = 250) -> np.ndarray:
    """Weights of the squared hinge with balanced classes and an offset of their own, by accelerated gradient steps."""
    sign = np.where(y == 1, 1.0, -1.0).astype(np.float32)
    weight = (sample_weight * np.where(y == 1, 0.5 / max((sample_weight * y).sum(), 1e-9), 0.5 / max((sample_weight * (1 - y)).sum(), 1e-9))).astype(np.float32)
    a = np.c_[x, np.ones(len(x))].astype(np.float32)
    top = np.ones(a.shape[1], dtype=np.float32)
    for _ in range(30):  # the largest curvature, by powers
        top = a.T @ (weight * (a @ top))
        top /= np.linalg.norm(top)
    step = np.float32(1 / (0.01 / cost + 2.2 * np.linalg.norm(a.T @ (weight * (a @ top)))))
    decay = np.r_[np.full(x.shape[1], 0.01 / cost), 0.0].astype(np.float32)
    w = v = np.zeros(a.shape[1], dtype=np.float32)
    for k in range(rounds):
        slack = np.maximum(0, 1 - sign * (a @ v))
        new = v - step * (v * decay - 2 * a.T @ (weight * sign * slack))
        v, w = new + np.float32(k / (k + 3)) * (new - w), new
    return w[:-1].astype(np.float64)


def calibrate(top: np.ndarray, y: np.ndarray, rate: float) -> tuple[np.ndarray, float, float]:
    """Slopes and offset of the logistic curve, with classes weighed to the ``rate`` of toxic labels, and the loss."""
    weight = np.where(y == 1, rate / max(y.sum(), 1), (1 - rate) / max((1 - y).sum(), 1))
    target = np.where(y == 1, 1 - 1 / (y.sum() + 2), 1 / ((1 - y).sum() + 2))
    a = np.c_[top, np.ones(len(top))]
    c = np.r_[np.ones(top.shape[1]), 0.0]
    for _ in range(80):
        p = 1 / (1 + np.exp(-np.clip(a @ c, -30, 30)))
        h = (a * (weight * p * (1 - p) + 1e-9)[:, None]).T @ a + 1e-6 * np.eye(len(c))
        c = c - np.clip(np.linalg.solve(h, a.T @ (weight * (p - target))), -2, 2)
    slope, offset = np.maximum(c[:-1], 0.0), float(c[-1])
    z = np.clip(top @ slope + offset, -30, 30)
    return slope, offset, float((weight * (np.log1p(np.exp(z)) - target * z)).sum())


def fit_toxicity(bags: list[set[str]], labels: list[int], rate: float, rounds: int = 8) -> dict:
    """The model from the texts' units: landmarks and their weights, what these come down to, slopes, offset.

    Every fourth text is kept from the rounds and says which round's machine is taken.
    """
    y = np.array(labels)
    empty = {"landmarks": [], "alpha": np.zeros(0), "characters": "", "weights": np.zeros(1), "slope": np.zeros(2), "offset": float(np.log((rate + 1e-6) / (1 - rate + 1e-6)))}
    aside = np.arange(len(y)) % 4 == 3
    if not len(y) or y.min() == y.max() or len(set(y[~aside])) < 2:
        return empty
    toxic, clean = ([b for b, k, z in zip(bags, y, aside) if k == kind and not z] for kind in (1, 0))
    landmarks, odds = pick_landmarks(toxic, clean)
    if not landmarks:
        return empty
    every = sorted(set().union(*bags))
    number = {w: k for k, w in enumerate(every)}
    lists = [np.array(sorted(map(number.__getitem__, b)), dtype=np.int64) for b in bags]
    in_clean = Counter(w for t in clean for w in t)
    against = sorted(in_clean, key=lambda w: (-in_clean[w], zlib.crc32(w.encode("utf-8", "surrogatepass")), w))[:CLEAN_UNITS]
    known = set(against)
    weight = np.sqrt(np.array([in_clean[w] for w in against] + [1.0] * (CLEAN_UNITS // 8)))
    against += broken_up([w for w in against if len(w) > ORDER][: CLEAN_UNITS // 8])
    weight = weight[: len(against)]
    gram = products(landmarks, landmarks)
    values, vectors = np.linalg.eigh((gram + gram.T) / 2)
    root = vectors @ np.diag(1 / np.sqrt(np.maximum(values, 1e-3))) @ vectors.T
    negative = products(against, landmarks) @ root

    def highest(own: np.ndarray, value: np.ndarray) -> list[str]:
        """The most telling unit, and the next ones that come near it."""
        v = value[own]
        top = np.argsort(-v, kind="stable")[:TOP]
        return [every[own[k]] for k in top if v[k] > max(0.0, NEAR * v[top[0]])]

    first = np.array([odds.get(w, 0.0) - 1 for w in every])
    witness = [highest(own, first) if k and not z else [] for own, k, z in zip(lists, y, aside)]
    best, least = None, np.inf
    for _ in range(rounds):
        shown = Counter(w for own in witness for w in own)
        names = sorted(shown)
        x = np.r_[products(names + broken_up(names), landmarks) @ root, negative]
        heavy = np.r_[[float(shown[w]) for w in names], [0.3 * shown[w] for w in names], weight]
        alpha = root @ train_svm(x, np.r_[np.ones(2 * len(names)), np.zeros(len(negative))], heavy)
        characters, weights = subsequence_weights(landmarks, alpha)
        margin = Scorer(characters, weights).margins(every)
        top = np.array([spoken(margin[own].tolist()) for own in lists])
        loss = calibrate(top[aside], y[aside], rate)[2] if len(set(y[aside])) > 1 else 0.0
        if loss < least:
            slope, offset, _ = calibrate(top, y, rate)
            least, best = loss, {"landmarks": landmarks, "alpha": alpha, "characters": characters, "weights": weights, "slope": slope, "offset": offset}
        before, witness = witness, [(highest(own, margin) or old) if k and not z else [] for own, old, k, z in zip(lists, witness, y, aside)]
        worst = Counter(every[own[margin[own].argmax()]] for own, k, z in zip(lists, y, aside) if not k and not z and len(own))
        hard = sorted(w for w in worst if w not in known and margin[number[w]] > 0)
        if witness == before and not hard:
            break
        known.update(hard)
        negative = np.r_[negative, products(hard, landmarks) @ root]
        weight = np.r_[weight, [float(worst[w]) for w in hard]]
    return best


def spoken(margins) -> tuple[float, float]:
    """What speaks for a text: the highest margin, and the mean of the next two."""
    top = heapq.nlargest(TOP, margins) + [0.0] * TOP
    return top[0], sum(top[1:TOP]) / (TOP - 1)


def score(model: dict, top: np.ndarray) -> np.ndarray:
    """Probabilities of texts whose highest units have these margins (``Scorer.texts``)."""
    return 1 / (1 + np.exp(-np.clip(top @ model["slope"] + model["offset"], -30, 30)))


def _bags(batches):
    for batch in batches:
        for lo in range(0, batch.num_rows, 64):
            part = batch.slice(lo, 64)
            bags = [units(t) for t in part.column("_text").to_pylist()]
            few = [sorted(b, key=lambda w: (zlib.crc32(w.encode("utf-8", "surrogatepass")), w))[:BAG_UNITS] if len(b) > BAG_UNITS else sorted(b) for b in bags]
            yield pa.RecordBatch.from_arrays([part.column("_id"), part.column("_y"), pa.array(few, pa.list_(pa.string()))], names=["_id", "_y", "bag"])


def learn_toxicity(docs: DataFrame, labels: DataFrame, text: str = "text", doc_id: str = "doc_id", label: str = "toxic", sample: int = SAMPLE) -> dict:
    """From labelled documents; the ids that are looked up are bounded by the sample, and so is what is collected."""
    known = labels.select(F.col(f"`{doc_id}`").alias("_id"), F.col(f"`{label}`").cast("int").alias("_y")).filter("_id is not null and _y in (0, 1)").withColumn("_h", F.xxhash64("_id"))
    sizes = {r["_y"]: r["n"] for r in known.groupBy("_y").agg(F.count(F.lit(1)).alias("n")).collect()}
    total = sum(sizes.values())
    picked = None
    for kind in sorted(sizes):
        own = known.filter(F.col("_y") == kind).orderBy("_h", "_id").limit(sample)  # the least hashes, kept task by task
        picked = own if picked is None else picked.unionByName(own)
    if picked is None:
        return fit_toxicity([], [], 0.0)
    texts = docs.select(F.col(f"`{doc_id}`").alias("_id"), F.col(f"`{text}`").cast("string").alias("_text")).filter("_text is not null")
    rows = texts.join(F.broadcast(picked.select("_id", "_y")), "_id").select("_id", "_y", "_text")
    schema = T.StructType([rows.schema["_id"], rows.schema["_y"], T.StructField("bag", T.ArrayType(T.StringType()))])
    bags = rows.mapInArrow(_bags, schema).orderBy(F.xxhash64("_id"), "_id", F.xxhash64("bag")).limit(4 * sample).select("bag", "_y").collect()
    return fit_toxicity([set(r["bag"]) for r in bags], [r["_y"] for r in bags], sizes.get(1, 0) / total)


def _scored(model: dict, least: float):
    few = {k: model[k] for k in ("characters", "weights", "slope", "offset")}
    key = hashlib.sha256(model["characters"].encode() + model["weights"].tobytes()).hexdigest()

    def run(batches):
        held = process_cache("toxicity")
        if key not in held:
            held.clear()
            held[key] = Scorer(few["characters"], few["weights"])
        own = held[key]
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                s = score(few, own.texts(part.column("_text").to_pylist()))
                yield pa.RecordBatch.from_arrays([part.column("_row"), pa.array(s), pa.array((s >= least).astype(np.int32))], names=["_row", "score", "predicted"])

    return run


def score_toxicity(docs: DataFrame, model: dict, text: str = "text", carry: list[str] | None = None, least: float = 0.3) -> DataFrame:
    """The columns ``carry`` (all, if None), ``score`` and ``predicted``, which take the place of such columns."""
    carry = [c for c in (docs.columns if carry is None else carry) if c not in ("score", "predicted")]
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in carry]).alias("_row"), F.col(f"`{text}`").cast("string").alias("_text"))
    schema = T.StructType([T.StructField("_row", rows.schema["_row"].dataType), T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])
    return rows.mapInArrow(_scored(model, least), schema).select(*[F.col("_row").getField(c).alias(c) for c in carry], "score", "predicted")
