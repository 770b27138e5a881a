"""The trainable student: a closed vocabulary, two linear maps over hashed features, greedy decoding.

Text becomes tokens: SQL and trace words, marks, slots ``T0..``/``C0..`` for the tables and
columns of the question's database, and ``Q0..`` for words copied from the question, so
that a literal that training never saw can still be written. A token's features (the tokens
before it, alone and with the question's words, the prompt style and the last trace step)
are hashed into ``BUCKETS`` rows. The base, both maps, is frozen at four bits a weight; each map
has its own low-rank adapter, and only the adapters are trained. The loss is the negative log
likelihood of the completion's tokens: prompt tokens are features and never targets.
"""

from __future__ import annotations

import math
import re
import zlib
from dataclasses import dataclass, field

import numpy as np

from .student import AdamW, EarlyStop, dequantize4, quantize4

BUCKETS = 1 << 14
END, UNKNOWN = "</s>", "<?>"
_TOKEN = re.compile(r"'(?:[^']|'')*'|### SQL|\w+|<=|>=|<>|=>|<-|[^\s\w]")
_ASKED = re.compile(r"[\w#&-]+")


def split_tokens(text: str) -> list[str]:
    return _TOKEN.findall(text)


def slots(tables: dict[str, list[str]]) -> dict[str, str]:
    """Names of a database's tables and columns to their slots."""
    columns = sorted({c for cols in tables.values() for c in cols} - set(tables))
    return {t: f"T{i}" for i, t in enumerate(sorted(tables))} | {c: f"C{i}" for i, c in enumerate(columns)}


def encode(text: str, question: str, names: dict[str, str]) -> list[str]:
    """Tokens of a completion, its names as slots and words of the question as copies."""
    asked = _ASKED.findall(question)
    out = []
    for w in split_tokens(text):
        bare = w[1:-1] if w.startswith("'") else w
        copied = (w.startswith("'") or w.isdigit() and len(w) > 1) and bare in asked
        out.append(("'" if w.startswith("'") else "") + f"Q{asked.index(bare)}" if copied else names.get(w, w))
    return out


def decode(tokens: list[str], question: str, names: dict[str, str]) -> str:
    """Text of tokens; spaces stand between words, which no grammar here minds."""
    asked, back = _ASKED.findall(question), {v: k for k, v in names.items()}
    out = []
    for w in tokens:
        m = re.fullmatch(r"('?)Q(\d+)", w)
        if m and int(m[2]) < len(asked):
            out.append(f"{m[1]}{asked[int(m[2])]}{m[1]}")
        else:
            out.append(back.get(w, w))
    return re.sub(r"(?<=\w) ?\. ?(?=\w)", ".", " ".join(out))


@dataclass
class Example:
    """One sample: prompt parts and, for training, the completion's tokens."""

    style: str
    question: str
    database: str
    target: list[str] = field(default_factory=list)


def _words(question: str) -> list[str]:
    return sorted({re.sub(r"\d", "#", w.lower()) for w in _ASKED.findall(question)})


class Features:
    """Rows of hashed features at the place after the tokens pushed so far; a step costs the
    same at every place."""

    def __init__(self, example: Example):
        self.style, self.asked = example.style, [*_words(example.question), f"db={example.database}"]
        self.last = ["<s>", "<s>", "<s>"]
        self.step, self.phase, self.since = "-", "trace", 0

    def push(self, token: str) -> None:
        """Takes up one token: a mark begins the SQL, a number after STEP the next step."""
        if token == "### SQL":
            self.phase, self.since = "sql", 0
        elif self.last[1] == "STEP":
            self.step = token
        self.since += 1
        self.last = [*self.last[1:], token]

    def rows(self) -> np.ndarray:
        c, b, a = self.last
        style, step, phase, since = self.style, self.step, self.phase, self.since
        keys = [f"1|{a}", f"2|{a}|{b}", f"3|{a}|{b}|{c}", f"s|{style}|{a}", f"t|{style}|{a}|{b}", f"p|{phase}|{a}", f"o|{step}|{a}|{b}", f"n|{phase}|{since}|{a}"]
        for w in self.asked:
            keys += (f"q|{a}|{w}", f"r|{a}|{b}|{w}", f"u|{a}|{phase}|{since}|{w}")
        return np.array([zlib.crc32(k.encode()) % BUCKETS for k in keys], np.int64)


@dataclass(frozen=True)
class Decode:
    """Limits of inference: tokens of the prompt and of the output."""

    max_in: int = 15_000
    max_out: int = 1_500


class Student:
    """Logits = (mean of feature rows of E') U' with W' = W + (alpha / r) A B for both maps."""

    def __init__(self, vocabulary: list[str], width: int = 64, r: int = 64, alpha: float = 128.0, seed: int = 42):
        self.vocabulary, self.index = vocabulary, {w: i for i, w in enumerate(vocabulary)}
        rng = np.random.default_rng(seed)
        shapes = {"e": (BUCKETS, width), "u": (width, len(vocabulary))}
        self.base = {"e": rng.normal(0, 0.3, shapes["e"]).astype(np.float32), "u": rng.normal(0, 0.05, shapes["u"]).astype(np.float32)}
        self.packed: dict[str, tuple] = {}
        self.r, self.scale = r, alpha / r
        self.part: dict[str, np.ndarray] = {}
        for k, (n, m) in shapes.items():
            self.part[f"{k}_a"] = rng.normal(0, 1 / math.sqrt(r), (n, r)).astype(np.float32) * 0.1
            self.part[f"{k}_b"] = np.zeros((r, m), np.float32)

    def quantise(self) -> Student:
        """Freezes the base at four bits a weight."""
        self.packed = {k: quantize4(w) for k, w in self.base.items()}
        self.base = {k: dequantize4(*p).astype(np.float32) for k, p in self.packed.items()}
        return self

    def n_trainable(self) -> int:
        return sum(p.size for p in self.part.values())

    def n_total(self) -> int:
        return self.n_trainable() + sum(w.size for w in self.base.values())

    def merged(self) -> tuple[np.ndarray, np.ndarray]:
        e, u = (self.base[k] + self.scale * self.part[f"{k}_a"] @ self.part[f"{k}_b"] for k in "eu")
        return e, u

    def places(self, examples: list[Example]) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Of each example the feature rows, the place of each, and the targets."""
        out = []
        for x in examples:
            f, target = Features(x), [*x.target, END]
            rows = []
            for w in target:
                rows.append(f.rows())
                f.push(w)
            at = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
            out.append((np.concatenate(rows), at, np.array([self.index.get(w, self.index[UNKNOWN]) for w in target])))
        return out

    def loss_grad(self, batch: list[tuple], grad: bool = True, full: bool = False) -> tuple[float, int, dict[str, np.ndarray]]:
        """Summed completion loss, its tokens, and gradients of the adapters (or, to pretrain a
        base, of the whole maps)."""
        ends = np.cumsum([len(t) for _, _, t in batch])
        rows = np.concatenate([x for x, _, _ in batch])
        at = np.concatenate([a + off for (_, a, _), off in zip(batch, [0, *ends[:-1]], strict=True)])
        y = np.concatenate([t for _, _, t in batch])
        n = len(y)
        sizes = np.bincount(at, minlength=n)
        weight = (1.0 / sizes).astype(np.float32)[at][:, None]
        used, place = np.unique(rows, return_inverse=True)
        scale = np.float32(self.scale)
        e = self.base["e"][used] + scale * self.part["e_a"][used] @ self.part["e_b"]
        u = self.base["u"] + scale * self.part["u_a"] @ self.part["u_b"]
        h = np.add.reduceat(e[place] * weight, np.concatenate([[0], np.cumsum(sizes)[:-1]]), axis=0)
        z = h @ u * 8.0
        z -= z.max(1, keepdims=True)
        p = np.exp(z)
        p /= p.sum(1, keepdims=True)
        loss = float(-np.log(p[np.arange(n), y].astype(np.float64) + 1e-30).sum())
        if not grad:
            return loss, n, {}
        p[np.arange(n), y] -= 1
        p *= 8.0
        order = np.argsort(place, kind="stable")
        back = ((p @ u.T)[at] * weight)[order]
        g_u, g_e = h.T @ p, np.add.reduceat(back, np.searchsorted(place[order], np.arange(len(used))), axis=0)
        if full:
            return loss, n, {"u": g_u, "e": (used, g_e)}
        return loss, n, {"u_a": scale * g_u @ self.part["u_b"].T, "u_b": scale * self.part["u_a"].T @ g_u, "e_a": (used, scale * g_e @ self.part["e_b"].T), "e_b": scale * self.part["e_a"][used].T @ g_e}

    def fit(self, train: list[Example], valid: list[Example], size: int = 6, epochs: int = 12, lr: float = 1e-4, seed: int = 42, full: bool = False, patience: int = 8, tol: float = 1e-3) -> list[dict]:
        """Adapters (or, if ``full``, the base itself) on the train part; evaluates four times an
        epoch on ``valid`` and puts the best state back. The curve has a row for each evaluation."""
        if not train:
            return []
        opt, rule, best, curve = AdamW(lr, wd=0.0), EarlyStop(patience, tol), None, []
        data, held = self.places(train), self.places(valid)
        target = self.base if full else self.part
        steps = math.ceil(len(data) / size)
        for epoch in range(epochs):
            order = np.random.default_rng((seed, epoch)).permutation(len(data))
            for b in range(steps):
                loss, n, grads = self.loss_grad([data[i] for i in order[b * size : (b + 1) * size]], full=full)
                opt.t += 1
                for k, g in grads.items():
                    if isinstance(g, tuple):  # rows that no feature of the batch uses stay
                        opt.step_rows(k, target[k], g[0], (g[1] / n).astype(np.float32))
                    else:
                        target[k] = opt.step(k, target[k], (g / n).astype(np.float32)).astype(np.float32)
                if held and ((b + 1) % max(1, steps // 4) == 0):
                    v_loss = v_n = 0
                    for i in range(0, len(held), 16):
                        one = self.loss_grad(held[i : i + 16], grad=False)
                        v_loss, v_n = v_loss + one[0], v_n + one[1]
                    v = v_loss / v_n
                    curve.append({"step": opt.t, "epoch": epoch + (b + 1) / steps, "train": loss / n, "loss": v})
                    if rule.better(v):
                        best = {k: w.copy() for k, w in target.items()}
                    if rule.done:
                        break
            if rule.done:
                break
        if best:
            target.update(best)
        return curve

    def nll(self, examples: list[Example]) -> tuple[float, int]:
        """Completion loss and tokens of examples: the prompt is no target."""
        loss, n, _ = self.loss_grad(self.places(examples), grad=False)
        return loss, n

    def greedy(self, example: Example, limits: Decode = Decode()) -> tuple[list[str], str]:
        """The most likely token each time, to the end or the cap: (tokens, finish reason)."""
        if len(split_tokens(example.question)) > limits.max_in:
            return [], "prompt too long"
        e, u = self._ready()
        f, made = Features(example), []
        while len(made) < limits.max_out:
            w = self.vocabulary[int((e[f.rows()].mean(0) @ u).argmax())]
            if w == END:
                return made, "end"
            made.append(w)
            f.push(w)
        return made, "length"

    def _ready(self) -> tuple[np.ndarray, np.ndarray]:
        if not hasattr(self, "_merged"):
            self._merged = self.merged()
        return self._merged

    def __getstate__(self) -> dict:
        """A four-bit base travels packed."""
        state = {k: v for k, v in self.__dict__.items() if k != "_merged"}
        return state | ({"base": None} if self.packed else {})

    def __setstate__(self, state: dict) -> None:
        self.__dict__.update(state)
        if self.base is None:
            self.base = {k: dequantize4(*p).astype(np.float32) for k, p in self.packed.items()}


def vocabulary(targets: list[list[str]]) -> list[str]:
    return [END, UNKNOWN, *sorted({w for t in targets for w in t})]
