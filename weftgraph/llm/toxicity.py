"""Toxicity scores from a bidirectional gated recurrent network in numpy.

Words enter as a vector of their own (for words of the training sample), the
final states of a character-level bidirectional recurrent net, and that net's
own judgement of the word. A second bidirectional recurrent net reads windows
of words, attention pools its states, and a linear layer gives the window's
logit. Every text is cut into overlapping windows that cover all of its words;
the document's logit is the largest of them.

Training runs on the driver over a bounded sample of labelled documents
(``TrainParams``), which is the only bound: scoring covers every word of every
row. Labels are read only from rows outside the held-out fold, and the model
sees nothing but text.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from weftgraph.llm.memory import give_back, make_room
from weftgraph.plans.common import ship

WINDOW, STRIDE = 64, 48
PIECE = 24  # bytes; longer words become several, so that all characters count
_CACHE_WORDS = 80_000
_STRIP = b".,;:!?#*%&$|\"'()[]{}<>=+-_/\\~^`@"


@dataclass(frozen=True)
class TrainParams:
    """Bounds of the labelled sample and of training."""

    toxic_docs: int = 1500
    clean_docs: int = 3000
    word_types: int = 60_000
    vocabulary: int = 8_000
    word_dim: int = 6
    char_dim: int = 8
    char_hidden: int = 8
    hidden: int = 8
    char_epochs: int = 4
    window_epochs: int = 5
    min_steps: int = 250
    seed: int = 17


# ---------------------------------------------------------------- the net


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


def _gru_init(rng, d: int, h: int) -> dict[str, np.ndarray]:
    return {"W": (rng.standard_normal((d, 3 * h)) / np.sqrt(d)).astype(np.float32), "U": (rng.standard_normal((h, 3 * h)) / np.sqrt(h)).astype(np.float32), "b": np.zeros(3 * h, np.float32)}


def gru_forward(p: dict, xw: np.ndarray) -> tuple[np.ndarray, list]:
    """States (T, B, H) for inputs already multiplied by W with b added."""
    t, b, h3 = xw.shape
    n = h3 // 3
    h, out, kept = np.zeros((b, n), np.float32), np.empty((t, b, n), np.float32), []
    for i in range(t):
        hu = h @ p["U"]
        gates = _sigmoid(xw[i, :, : 2 * n] + hu[:, : 2 * n])
        z, r = gates[:, :n], gates[:, n:]
        c = np.tanh(xw[i, :, 2 * n :] + r * hu[:, 2 * n :])
        kept.append((h, z, r, c, hu[:, 2 * n :]))
        h = c + z * (h - c)
        out[i] = h
    return out, kept


def gru_backward(p: dict, kept: list, dout: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Gradients of the multiplied inputs and of U."""
    t, b, n = dout.shape
    dxw, du = np.empty((t, b, 3 * n), np.float32), np.zeros_like(p["U"])
    dh = np.zeros((b, n), np.float32)
    for i in range(t - 1, -1, -1):
        h, z, r, c, huc = kept[i]
        dh = dh + dout[i]
        dz = dh * (h - c) * z * (1 - z)
        dc = dh * (1 - z) * (1 - c * c)
        dr = dc * huc * r * (1 - r)
        dhu = np.concatenate([dz, dr, dc * r], axis=1)
        dxw[i] = np.concatenate([dz, dr, dc], axis=1)
        du += h.T @ dhu
        dh = dh * z + dhu @ p["U"].T
    return dxw, du


class _Adam:
    def __init__(self, params: dict[str, np.ndarray], rate: float):
        self.p, self.rate, self.t = params, rate, 0
        self.m = {k: np.zeros_like(v) for k, v in params.items()}
        self.v = {k: np.zeros_like(v) for k, v in params.items()}

    def step(self, grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, g in grads.items():
            g = np.clip(g, -5, 5)
            self.m[k] += 0.1 * (g - self.m[k])
            self.v[k] += 0.01 * (g * g - self.v[k])
            self.p[k] -= self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.99**self.t)) + 1e-7)


def _reversed_index(lengths: np.ndarray, t: int) -> np.ndarray:
    """Place of step i counted from each sequence's end; padding stays last."""
    i = np.arange(t)[:, None]
    return np.where(i < lengths[None, :], lengths[None, :] - 1 - i, i)


def _char_input(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    lengths = np.array([max(1, len(w)) for w in words])
    flat = np.zeros((int(lengths.max()), len(words)), np.uint8)
    for j, w in enumerate(words):
        flat[: len(w), j] = np.frombuffer(w, np.uint8)
    return flat, lengths


class Model:
    """Parameters, with forward passes for words and windows."""

    def __init__(self, params: dict[str, np.ndarray], vocabulary: dict[bytes, int], shift: float, empty_logit: float):
        self.p, self.vocabulary, self.shift, self.empty_logit = params, vocabulary, shift, empty_logit

    def gru(self, name: str) -> dict[str, np.ndarray]:
        return {k: self.p[f"{name}.{k}"] for k in ("W", "U", "b")}

    def chars(self, words: list[bytes]) -> np.ndarray:
        """(n, 2 x char_hidden + 1): final states of both directions and the word's logit."""
        order = sorted(range(len(words)), key=lambda i: len(words[i]))
        h = self.p["cf.U"].shape[0]
        out = np.empty((len(words), 2 * h + 1), np.float32)
        for at in range(0, len(order), 4096):
            part = order[at : at + 4096]
            codes, lengths = _char_input([words[i] for i in part])
            ends = self.char_states(codes, lengths)[0]
            out[part, : 2 * h] = ends
            out[part, 2 * h] = np.tanh(0.25 * (ends @ self.p["ch.w"] + self.p["ch.b"]))
        return out

    def char_states(self, codes: np.ndarray, lengths: np.ndarray):
        t, col = codes.shape[0], np.arange(codes.shape[1])
        back = codes[_reversed_index(lengths, t), col[None, :]]
        states, kept = [], []
        for name, c in (("cf", codes), ("cb", back)):
            g = self.gru(name)
            s, k = gru_forward(g, (self.p["ce"] @ g["W"] + g["b"])[c])
            states.append(s[lengths - 1, col])
            kept.append((k, c, s.shape))
        return np.concatenate(states, axis=1), kept

    def word_inputs(self, words: list[bytes]) -> np.ndarray:
        rows = np.array([self.vocabulary.get(w, 0) for w in words])
        return np.concatenate([self.p["we"][rows], self.chars(words)], axis=1)

    def window_logits(self, xf: np.ndarray, xb: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Logits for multiplied inputs (T, B, 3H) of both directions."""
        t, b, _ = xf.shape
        hf = gru_forward(self.gru("wf"), xf)[0]
        hb = gru_forward(self.gru("wb"), xb)[0][_reversed_index(lengths, t), np.arange(b)[None, :]]
        states = np.concatenate([hf, hb], axis=2)
        a = np.tanh(states @ self.p["at.W"]) @ self.p["at.v"]
        a = np.where(np.arange(t)[:, None] < lengths[None, :], a, -1e9)
        a = np.exp(a - a.max(axis=0))
        a /= a.sum(axis=0)
        pooled = np.einsum("tb,tbh->bh", a, states)
        return pooled @ self.p["o.w"] + self.p["o.b"][0]


def words_of(text: str | None) -> list[bytes]:
    return (text or "").lower().encode("utf-8", "surrogatepass").split()


def pieces_of(word: bytes) -> list[bytes]:
    """The word without marks at its ends (itself if nothing else is in it), in pieces of at most PIECE bytes."""
    w = word.strip(_STRIP) or word
    return [w[i : i + PIECE] for i in range(0, len(w), PIECE)]


def windows_of(n: int) -> list[tuple[int, int]]:
    """Overlapping windows over n words, the last one ending at the last word."""
    out, at = [], 0
    while True:
        out.append((at, min(WINDOW, n - at)))
        if at + WINDOW >= n:
            return out
        at += STRIDE


# ---------------------------------------------------------------- training


def _bce(logit: np.ndarray, y: np.ndarray, w: np.ndarray) -> np.ndarray:
    return (_sigmoid(logit) - y) * w / max(1e-6, w.sum())


def train(texts: list[str], toxic: list[int], params: TrainParams = TrainParams()) -> Model | None:
    """Fit the nets; None if the sample lacks one of the classes."""
    y_doc = np.array(toxic)
    if not len(y_doc) or y_doc.min() == y_doc.max():
        return None
    rng = np.random.default_rng(params.seed)
    docs = [[p for w in words_of(t) for p in pieces_of(w)] for t in texts]
    in_toxic, in_clean = Counter(), Counter()
    for d, y in zip(docs, y_doc, strict=True):
        (in_toxic if y else in_clean).update(set(d))
    share = float(y_doc.mean())
    known = vocabulary_of(in_toxic, in_clean, share, params.vocabulary)
    vocabulary = {w: i + 1 for i, w in enumerate(known)}
    h, ch, d = params.hidden, params.char_hidden, params.word_dim + 2 * params.char_hidden + 1
    p: dict[str, np.ndarray] = {"ce": (0.3 * rng.standard_normal((256, params.char_dim))).astype(np.float32), "ch.w": np.zeros(2 * ch, np.float32), "ch.b": np.zeros(1, np.float32)}
    for name, size, hid in (("cf", params.char_dim, ch), ("cb", params.char_dim, ch), ("wf", d, h), ("wb", d, h)):
        p |= {f"{name}.{k}": v for k, v in _gru_init(rng, size, hid).items()}
    p |= {"we": np.zeros((len(vocabulary) + 1, params.word_dim), np.float32), "at.W": (rng.standard_normal((2 * h, h)) / 4).astype(np.float32), "at.v": (rng.standard_normal(h) / 2).astype(np.float32), "o.w": (rng.standard_normal(2 * h) / 4).astype(np.float32), "o.b": np.zeros(1, np.float32)}
    model = Model(p, vocabulary, 0.0, 0.0)
    _train_chars(model, in_toxic, in_clean, share, params, rng)
    # a word's own vector starts from the evidence that the word itself is toxic
    p["we"][1:, 0] = np.clip(_evidence(np.array([in_toxic[w] for w in known]), np.array([in_clean[w] for w in known]), share), -6, 6) / 6
    _train_windows(model, docs, y_doc, params, rng)
    scorer = _Scorer(model)
    best = np.concatenate([scorer.logits(texts[i : i + 512]) for i in range(0, len(texts), 512)])
    model.shift = _threshold(np.where(np.isinf(best), -10.0, best), y_doc)
    model.empty_logit = float(np.log(share / (1 - share))) if share < 0.5 else -1.0
    return model


def vocabulary_of(in_toxic: Counter, in_clean: Counter, share: float, size: int) -> list[bytes]:
    """Words with a vector of their own: all that mark toxic documents, then the most frequent up to ``size``.

    Words that mark toxic documents can be rare, the more so in languages with
    few labelled documents, and by frequency alone they would be left out.
    """
    words = sorted((w for w in in_toxic.keys() | in_clean.keys() if in_toxic[w] + in_clean[w] >= 3), key=lambda w: (-(in_toxic[w] + in_clean[w]), w))
    marks = {w for w in words if _evidence(in_toxic[w], in_clean[w], share) > 0}
    rest = [w for w in words if w not in marks]
    return [w for w in words if w in marks] + rest[: max(0, size - len(marks))]


def _evidence(k: np.ndarray, c: np.ndarray, share: float) -> np.ndarray:
    """Log odds that a word in k toxic and c clean documents marks toxic ones.

    Against a neutral word, found in toxic documents at their share, stands
    one of whose documents 97 in 100 are labelled toxic; one word in a
    thousand is expected to be like that.
    """
    return np.log(0.001) + k * np.log(0.97 / share) + c * np.log(0.03 / (1 - share))


def _train_chars(model: Model, in_toxic: Counter, in_clean: Counter, share: float, params: TrainParams, rng) -> None:
    """Characters: the target of a word is the chance that it marks toxic documents."""
    types = sorted(in_toxic.keys() | in_clean.keys())
    if len(types) > params.word_types:
        keep = set(sorted((w for w in types if not in_clean[w]), key=lambda w: (-in_toxic[w], w))[: params.word_types // 2])
        rest = [w for w in types if w not in keep]
        types = sorted(keep | {rest[i] for i in rng.choice(len(rest), min(len(rest), params.word_types - len(keep)), replace=False)})
    k, clean = np.array([in_toxic[w] for w in types], np.float64), np.array([in_clean[w] for w in types], np.float64)
    y = _sigmoid(np.clip(_evidence(k, clean, share), -30, 30)).astype(np.float32)
    weight = (1 + 8 * np.maximum(0, y - 0.5) + np.log1p(clean)).astype(np.float32)
    adam = _Adam(model.p, 0.01)
    order = np.array(sorted(range(len(types)), key=lambda i: len(types[i])))
    batches = [order[i : i + 1024] for i in range(0, len(order), 1024)]
    epochs = max(params.char_epochs, -(-params.min_steps // len(batches)))
    for epoch in range(epochs):
        adam.rate = 0.01 if epoch < epochs - 1 else 0.003
        for b in rng.permutation(len(batches)):
            part = batches[b]
            codes, lengths = _char_input([types[i] for i in part])
            ends, kept = model.char_states(codes, lengths)
            dlogit = _bce(ends @ model.p["ch.w"] + model.p["ch.b"], y[part], weight[part]).astype(np.float32)
            grads = {"ch.w": ends.T @ dlogit, "ch.b": dlogit.sum(keepdims=True), "ce": np.zeros_like(model.p["ce"])}
            dends, n = np.outer(dlogit, model.p["ch.w"]), params.char_hidden
            for j, (name, (k_, c, shape)) in enumerate(zip(("cf", "cb"), kept, strict=True)):
                dout = np.zeros(shape, np.float32)
                dout[lengths - 1, np.arange(len(part))] = dends[:, j * n : (j + 1) * n]
                dxw, du = gru_backward(model.gru(name), k_, dout)
                table = np.zeros((256, 3 * n), np.float32)
                np.add.at(table, c.ravel(), dxw.reshape(-1, 3 * n))
                grads |= {f"{name}.U": du, f"{name}.W": model.p["ce"].T @ table, f"{name}.b": table.sum(axis=0)}
                grads["ce"] += table @ model.p[f"{name}.W"].T
            adam.step(grads)


def _train_windows(model: Model, docs: list[list[bytes]], y_doc: np.ndarray, params: TrainParams, rng) -> None:
    """Windows: of toxic documents the most suspect one, of clean ones the most suspect and a random one.

    At each step half of the words that are not suspect are replaced by words
    drawn from clean documents, so that windows can't be learned by heart.
    """
    types = sorted({w for d in docs for w in d})
    index = {w: i for i, w in enumerate(types)}
    chars = model.chars(types)
    suspect = chars[:, -1] + model.p["we"][[model.vocabulary.get(w, 0) for w in types], 0]
    rows = np.array([model.vocabulary.get(w, 0) for w in types])
    windows, labels = [], []
    for words, y in zip(docs, y_doc, strict=True):
        if not words:
            continue
        at = np.array([index[w] for w in words])
        spans = windows_of(len(at))
        top = [suspect[at[s : s + n]].max() for s, n in spans]
        picks = {int(np.argmax(top))} | (set() if y else {int(rng.integers(len(spans)))})
        for i in sorted(picks):
            windows.append(at[spans[i][0] : spans[i][0] + spans[i][1]])
            labels.append(y)
    pool = np.array([index[w] for words, y in zip(docs, y_doc, strict=True) if not y for w in words])
    pool = pool[rng.integers(len(pool), size=min(len(pool), 200_000))] if len(pool) else np.zeros(1, np.int64)
    calm = suspect <= 0
    labels, lengths = np.array(labels, np.float32), np.array([len(w) for w in windows])
    weight = np.where(labels == 1, 0.5 / max(1, labels.sum()), 0.5 / max(1, (1 - labels).sum())).astype(np.float32)
    order = np.argsort(lengths, kind="stable")
    batches = [order[i : i + 128] for i in range(0, len(order), 128)]
    adam, n = _Adam(model.p, 0.01), params.hidden
    epochs = max(params.window_epochs, -(-params.min_steps // len(batches)))
    for epoch in range(epochs):
        adam.rate = 0.01 if epoch < epochs - 1 else 0.003
        for b in rng.permutation(len(batches)):
            part = batches[b]
            size, t = len(part), int(lengths[part].max())
            ids = np.zeros((t, size), np.int64)
            for j, i in enumerate(part):
                ids[: lengths[i], j] = windows[i]
            swap = calm[ids] & (rng.random(ids.shape) < 0.5)
            ids[swap] = pool[rng.integers(len(pool), size=int(swap.sum()))]
            flip = _reversed_index(lengths[part], t)
            col = np.arange(size)[None, :]
            x = np.concatenate([model.p["we"][rows[ids]], chars[ids]], axis=2)
            xr = x[flip, col]
            f, r = model.gru("wf"), model.gru("wb")
            hf, kf = gru_forward(f, x @ f["W"] + f["b"])
            hr, kr = gru_forward(r, xr @ r["W"] + r["b"])
            states = np.concatenate([hf, hr[flip, col]], axis=2)
            u = np.tanh(states @ model.p["at.W"])
            inside = np.arange(t)[:, None] < lengths[part][None, :]
            a = np.where(inside, u @ model.p["at.v"], -1e9)
            a = np.exp(a - a.max(axis=0))
            a = (a / a.sum(axis=0)).astype(np.float32)
            pooled = np.einsum("tb,tbh->bh", a, states)
            dlogit = _bce(pooled @ model.p["o.w"] + model.p["o.b"], labels[part], weight[part]).astype(np.float32)
            dpooled = np.outer(dlogit, model.p["o.w"])
            da = np.einsum("bh,tbh->tb", dpooled, states)
            ds = a * (da - (a * da).sum(axis=0))
            du_ = ds[:, :, None] * model.p["at.v"] * (1 - u * u)
            dstates = a[:, :, None] * dpooled[None] + du_ @ model.p["at.W"].T
            grads = {"o.w": pooled.T @ dlogit, "o.b": dlogit.sum(keepdims=True), "at.v": np.einsum("tb,tbh->h", ds, u), "at.W": np.einsum("tbi,tbj->ij", states, du_)}
            dxf, grads["wf.U"] = gru_backward(f, kf, dstates[:, :, :n])
            dxr, grads["wb.U"] = gru_backward(r, kr, dstates[:, :, n:][flip, col])
            grads |= {"wf.W": np.einsum("tbi,tbj->ij", x, dxf), "wf.b": dxf.sum(axis=(0, 1)), "wb.W": np.einsum("tbi,tbj->ij", xr, dxr), "wb.b": dxr.sum(axis=(0, 1))}
            dx = dxf @ f["W"].T + (dxr @ r["W"].T)[flip, col]
            dwe = np.zeros_like(model.p["we"])
            np.add.at(dwe, rows[ids][inside], dx[inside][:, : params.word_dim])
            dwe[0] = 0
            adam.step(grads | {"we": dwe})


def _threshold(logits: np.ndarray, y: np.ndarray) -> float:
    """The cut with the fewest errors on the sample, in the middle of its gap."""
    order = np.argsort(logits, kind="stable")
    s, t = logits[order], y[order]
    wrong = np.concatenate([[np.sum(t == 0)], np.sum(t == 0) - np.cumsum(t == 0) + np.cumsum(t == 1)])
    good = np.flatnonzero(wrong == wrong.min())
    cuts = np.concatenate([[s[0] - 1], (s[1:] + s[:-1]) / 2, [s[-1] + 1]])
    gaps = np.concatenate([[1.0], s[1:] - s[:-1], [1.0]])
    return float(cuts[good[np.argmax(gaps[good])]])


# ---------------------------------------------------------------- scoring


class _Scorer:
    def __init__(self, model: Model):
        self.m, h3 = model, model.p["wf.b"].shape[0]
        self.f, self.b = model.gru("wf"), model.gru("wb")
        self.h3, self.rows, self.size = h3, {}, 0
        self.table = np.empty((1024, 2 * h3), np.float32)

    def index(self, docs: list[list[bytes]]) -> list[np.ndarray]:
        """Rows of the table for each document's word pieces; new words are added."""
        if self.size > _CACHE_WORDS:
            self.rows, self.size = {}, 0
        new = list({w for d in docs for w in d}.difference(self.rows))
        parts = {w: pieces_of(w) for w in new}
        fresh = sorted({p for ps in parts.values() for p in ps})
        if fresh:
            x = self.m.word_inputs(fresh)
            need = self.size + len(fresh)
            if need > len(self.table):
                self.table = np.concatenate([self.table[: self.size], np.empty((max(need, 2 * self.size) - self.size, 2 * self.h3), np.float32)])
            self.table[self.size : need] = np.concatenate([x @ self.f["W"] + self.f["b"], x @ self.b["W"] + self.b["b"]], axis=1)
            at = {p: self.size + i for i, p in enumerate(fresh)}
            self.size = need
            for w, ps in parts.items():
                self.rows[w] = at[ps[0]] if len(ps) == 1 else tuple(at[p] for p in ps)
        out = []
        for d in docs:
            got = list(map(self.rows.__getitem__, d))
            if any(type(g) is tuple for g in got):
                got = [y for g in got for y in (g if type(g) is tuple else (g,))]
            out.append(np.array(got, np.int64))
        return out

    def logits(self, texts: list[str | None]) -> np.ndarray:
        """The largest window logit of each text; minus infinity without words."""
        ids = self.index([words_of(t) for t in texts])
        spans = [(j, s, n) for j, x in enumerate(ids) if len(x) for s, n in windows_of(len(x))]
        logits = np.full(len(texts), -np.inf)
        spans.sort(key=lambda w: w[2])
        for at in range(0, len(spans), 512):
            part = spans[at : at + 512]
            lengths = np.array([n for _, _, n in part])
            t = int(lengths.max())
            rows = np.zeros((t, len(part)), np.int64)
            for j, (d, s, n) in enumerate(part):
                rows[:n, j] = ids[d][s : s + n]
            back = rows[_reversed_index(lengths, t), np.arange(len(part))[None, :]]
            got = self.m.window_logits(self.table[rows, : self.h3], self.table[back, self.h3 :], lengths)
            np.maximum.at(logits, np.array([d for d, _, _ in part]), got)
        return logits

    def scores(self, texts: list[str | None]) -> np.ndarray:
        logits = self.logits(texts)
        return _sigmoid(np.where(np.isinf(logits), self.m.empty_logit, logits - self.m.shift))


def _score_batches(model: Model | None, text_col: str, carry_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room("toxicity")
        scorer = _Scorer(model) if model else None
        for batch in batches:
            i = batch.schema.get_field_index(text_col)
            kept = [j for j in range(batch.num_columns) if carry_text or j != i]
            for at in range(0, batch.num_rows, 256):  # small batches leave, so that no copy of a whole one is held
                some = batch.slice(at, 256)
                score = scorer.scores(some.column(i).to_pylist()) if scorer else np.zeros(some.num_rows)
                yield pa.RecordBatch.from_arrays([*[some.column(j) for j in kept], pa.array(score, pa.float64())], names=[*[batch.schema.names[j] for j in kept], "_score"])
        batch = some = scorer = None  # else they outlive this
        give_back()

    return run


def held_out(id_col: Column, folds: int = 5) -> Column:
    """The fold that training never reads: crc32 of the id as text, modulo folds, is 0."""
    return F.coalesce(F.pmod(F.crc32(id_col.cast("string")), F.lit(folds)) == 0, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, params: TrainParams = TrainParams(), id_col: str = "doc_id", text_col: str = "text") -> Model | None:
    """Train on a sample of the labelled rows outside the held-out fold.

    The sample takes, of each class, the documents with the smallest hashes of
    their ids, up to the bounds of ``params``. Rows without a label, a text or
    an id take no part; a document labelled twice counts as toxic if one label
    says so.
    """
    open_rows = labels.where(F.col("toxic").isNotNull() & F.col(id_col).isNotNull() & ~held_out(F.col(id_col)))
    known = open_rows.groupBy(id_col).agg(F.max("toxic").alias("toxic"))
    picked = [r for y, n in ((1, params.toxic_docs), (0, params.clean_docs)) for r in known.where(F.col("toxic") == y).orderBy(F.xxhash64(id_col), id_col).limit(n).collect()]
    if not picked:
        return None
    label = {r[id_col]: int(r["toxic"]) for r in picked}
    wanted = docs.sparkSession.createDataFrame([(i,) for i in sorted(label)], "_wanted long")  # bounded by params
    rows = docs.where(F.col(text_col).isNotNull()).join(F.broadcast(wanted), F.col(id_col) == F.col("_wanted"), "left_semi").select(id_col, text_col).collect()
    first = {}
    for r in sorted(rows, key=lambda r: (r[id_col], r[text_col])):
        first.setdefault(r[id_col], r[text_col])
    ids = sorted(first)
    return train([first[i] for i in ids], [label[i] for i in ids], params)


def score_toxicity(docs: DataFrame, labels: DataFrame, params: TrainParams = TrainParams(), id_col: str = "doc_id", text_col: str = "text", carry_text: bool = True) -> DataFrame:
    """The input rows and score, predicted, held_out.

    ``carry_text=False`` leaves the text itself out of the result.
    Null and empty texts get the share of toxic rows in the sample, if that is
    below one half. Without labels of both classes every score is 0. Repeated
    rows and null ids are scored like any other. Columns of the input that
    have one of the new names are replaced.
    """
    ship(docs.sparkSession)
    model = fit(docs, labels, params, id_col, text_col)
    rows = docs.drop("score", "predicted", "held_out")
    fields = [f for f in rows.schema.fields if carry_text or f.name != text_col]
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in fields] + ["_score double"])
    out = rows.mapInArrow(_score_batches(model, text_col, carry_text), schema)
    return out.withColumnsRenamed({"_score": "score"}).withColumns({"predicted": F.when(F.col("score") >= 0.5, 1).otherwise(0), "held_out": held_out(F.col(id_col))})
