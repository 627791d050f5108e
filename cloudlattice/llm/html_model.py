"""Recurrent block labeller: a bidirectional LSTM in numpy over the blocks of a page.

A block is read as the sum of embeddings of its hashed tag path (tags, and words of
class, id and role), the mean of embeddings of its hashed words, and a few
measures of length, links and punctuation. Both directions see the whole page, so
a block's label depends on what stands around it.
"""

from __future__ import annotations

import math
import zlib
from pathlib import Path

import numpy as np

from cloudlattice.llm.html_blocks import Block

PATH_ROWS, PATH_DIM = 1024, 24
WORD_ROWS, WORD_DIM = 2048, 8
MEASURES = 6
HIDDEN = 20
INPUT = PATH_DIM * 2 + WORD_DIM + MEASURES
WEIGHTS = Path(__file__).with_name("html_model.npz")
Params = dict[str, np.ndarray]


def slot(value: str, rows: int) -> int:
    return zlib.crc32(value.encode("utf-8", "replace")) % rows


def inputs(block: Block) -> tuple[list[int], list[int], list[int], list[float]]:
    """Hashes of the whole path, of its last three parts, of the words, and the measures."""
    words = block.text.lower().split()
    n = len(block.text)
    marks = sum(block.text.count(c) for c in ".,;:!?")
    measures = [math.log1p(n) / 8, math.log1p(len(words)) / 6, block.linked / max(n, 1), min(marks / max(len(words), 1), 1.0), float(block.text[-1:] in ".!?:\"'”»"), sum(map(str.isdigit, block.text)) / max(n, 1)]
    return [slot(p, PATH_ROWS) for p in block.path], [slot(f"<{p}", PATH_ROWS) for p in block.path[-3:]], [slot(w, WORD_ROWS) for w in words], measures


def initial(seed: int = 0) -> Params:
    rng = np.random.default_rng(seed)
    p: Params = {"path": rng.normal(0, 0.1, (PATH_ROWS, PATH_DIM)), "tail": rng.normal(0, 0.1, (PATH_ROWS, PATH_DIM)), "word": np.zeros((WORD_ROWS, WORD_DIM))}
    for d in ("f", "b"):
        p[f"w{d}"] = rng.normal(0, 1 / math.sqrt(INPUT), (INPUT, 4 * HIDDEN))
        p[f"u{d}"] = rng.normal(0, 1 / math.sqrt(HIDDEN), (HIDDEN, 4 * HIDDEN))
        p[f"c{d}"] = np.r_[np.zeros(HIDDEN), np.ones(HIDDEN), np.zeros(2 * HIDDEN)]
    p["out"], p["bias"] = rng.normal(0, 0.1, 2 * HIDDEN + INPUT), np.zeros(1)
    return p


def embedded(p: Params, pages: list[list[tuple]]) -> tuple[np.ndarray, np.ndarray]:
    """(pages, blocks, INPUT) and the mask of real blocks; shorter pages are padded."""
    most = max(len(x) for x in pages)
    x, mask = np.zeros((len(pages), most, INPUT)), np.zeros((len(pages), most))
    for i, page in enumerate(pages):
        mask[i, : len(page)] = 1
        for t, (path, tail, words, measures) in enumerate(page):
            if path:
                x[i, t, :PATH_DIM] = p["path"][path].sum(0)
                x[i, t, PATH_DIM : 2 * PATH_DIM] = p["tail"][tail].sum(0)
            if words:
                x[i, t, 2 * PATH_DIM : 2 * PATH_DIM + WORD_DIM] = p["word"][words].mean(0)
            x[i, t, -MEASURES:] = measures
    return x, mask


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def lstm(p: Params, x: np.ndarray, mask: np.ndarray, d: str, keep: bool = False):
    """Hidden states in page order; ``d`` is f (forward) or b (backward). Padding leaves the state as it was."""
    n, most, _ = x.shape
    given = x @ p[f"w{d}"] + p[f"c{d}"]
    h, c = np.zeros((n, HIDDEN)), np.zeros((n, HIDDEN))
    states, tape = np.zeros((n, most, HIDDEN)), []
    for t in range(most) if d == "f" else range(most - 1, -1, -1):
        z = given[:, t] + h @ p[f"u{d}"]
        i, f, o = (_sigmoid(z[:, k * HIDDEN : (k + 1) * HIDDEN]) for k in range(3))
        g = np.tanh(z[:, 3 * HIDDEN :])
        m = mask[:, t : t + 1]
        new = f * c + i * g
        th = np.tanh(new)
        if keep:
            tape.append((t, h, c, i, f, o, g, th, m))
        h, c = m * (o * th) + (1 - m) * h, m * new + (1 - m) * c
        states[:, t] = h
    return states, tape


def probabilities(p: Params, pages: list[list[tuple]]) -> list[np.ndarray]:
    """For each page the probability of each block to be main text; pages of like length run together."""
    out: list[np.ndarray] = [np.zeros(0)] * len(pages)
    order = sorted((k for k in range(len(pages)) if pages[k]), key=lambda k: len(pages[k]))
    for start in range(0, len(order), 64):
        part = order[start : start + 64]
        x, mask = embedded(p, [pages[k] for k in part])
        both = np.concatenate([lstm(p, x, mask, "f")[0], lstm(p, x, mask, "b")[0], x], axis=2)
        prob = _sigmoid(both @ p["out"] + p["bias"])
        for row, k in enumerate(part):
            out[k] = prob[row, : len(pages[k])]
    return out


def gradients(p: Params, pages: list[list[tuple]], truth: list[list[int]]) -> tuple[float, Params]:
    """Mean cross-entropy over blocks and its gradient by back-propagation through both directions."""
    x, mask = embedded(p, pages)
    y = np.zeros(mask.shape)
    for i, t in enumerate(truth):
        y[i, : len(t)] = t
    states = {d: lstm(p, x, mask, d, keep=True) for d in ("f", "b")}
    both = np.concatenate([states["f"][0], states["b"][0], x], axis=2)
    prob = _sigmoid(both @ p["out"] + p["bias"])
    n = mask.sum()
    loss = float(-(mask * (y * np.log(prob + 1e-9) + (1 - y) * np.log(1 - prob + 1e-9))).sum() / n)
    delta = mask * (prob - y) / n
    g: Params = {"out": np.einsum("nt,ntk->k", delta, both), "bias": np.array([delta.sum()])}
    back = delta[:, :, None] * p["out"]
    dx = back[:, :, 2 * HIDDEN :].copy()
    for k, d in enumerate(("f", "b")):
        dh_out = back[:, :, k * HIDDEN : (k + 1) * HIDDEN]
        dh, dc = np.zeros((len(pages), HIDDEN)), np.zeros((len(pages), HIDDEN))
        gw, gu, gc = np.zeros_like(p[f"w{d}"]), np.zeros_like(p[f"u{d}"]), np.zeros_like(p[f"c{d}"])
        for t, h0, c0, i, f, o, gg, th, m in reversed(states[d][1]):
            dh = dh + dh_out[:, t]
            dnew = m * dc + m * dh * o * (1 - th**2)
            dz = np.concatenate([dnew * gg * i * (1 - i), dnew * c0 * f * (1 - f), m * dh * th * o * (1 - o), dnew * i * (1 - gg**2)], axis=1)
            gw += x[:, t].T @ dz
            gu += h0.T @ dz
            gc += dz.sum(0)
            dx[:, t] += dz @ p[f"w{d}"].T
            dh, dc = dz @ p[f"u{d}"].T + (1 - m) * dh, dnew * f + (1 - m) * dc
        g[f"w{d}"], g[f"u{d}"], g[f"c{d}"] = gw, gu, gc
    for name, lo, hi, at in (("path", 0, PATH_DIM, 0), ("tail", PATH_DIM, 2 * PATH_DIM, 1), ("word", 2 * PATH_DIM, 2 * PATH_DIM + WORD_DIM, 2)):
        g[name] = np.zeros_like(p[name])
        for i, page in enumerate(pages):
            for t, parts in enumerate(page):
                if parts[at]:
                    np.add.at(g[name], parts[at], dx[i, t, lo:hi] / (len(parts[at]) if name == "word" else 1))
    return loss, g


def save(p: Params, path: Path = WEIGHTS) -> None:
    np.savez_compressed(path, **{k: v.astype(np.float16) for k, v in p.items()})


def restore(path: Path = WEIGHTS) -> Params:
    with np.load(path) as held:
        return {k: held[k].astype(np.float64) for k in held.files}
