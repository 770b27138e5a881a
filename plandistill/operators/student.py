"""A compact student: counts, completion loss, 4-bit base, low-rank adapter, training, decoding."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

# --- counts: the closed form that minimises the loss, and its NLL -----------------------------


def bigrams(texts: DataFrame, by: list[str]) -> DataFrame:
    """``by`` columns, prev and tok for each token of ``text``; the first follows an empty string."""
    toks = F.regexp_extract_all(F.lower("text"), F.lit("[a-z0-9]+"), F.lit(0))
    rows = texts.select(*by, F.posexplode(toks).alias("pos", "tok"))
    return rows.withColumn("prev", F.coalesce(F.lag("tok").over(Window.partitionBy(*by).orderBy("pos")), F.lit("")))


def count_nll(pairs: DataFrame, train: DataFrame, by: list[str], k: float = 1.0) -> DataFrame:
    """Add-k bigram NLL of ``pairs`` by ``by`` with counts of ``train``: nll and n_tok."""
    pair = train.groupBy("prev", "tok").agg(F.count("*").alias("c"))
    ctx = train.groupBy("prev").agg(F.count("*").alias("cc"))
    v = train.agg((F.countDistinct("tok") + 1).alias("v"))
    scored = pairs.join(pair, ["prev", "tok"], "left").join(ctx, "prev", "left").join(F.broadcast(v))
    p = (F.coalesce("c", F.lit(0)) + k) / (F.coalesce("cc", F.lit(0)) + k * F.col("v"))
    return scored.groupBy(*by).agg(F.round(F.sum(-F.ln(p)), 6).alias("nll"), F.count("*").alias("n_tok"))


# --- quantised base and adapter ----------------------------------------------------------------

def normal_levels() -> np.ndarray:
    """Sixteen levels in [-1, 1] at even quantiles of a normal distribution: seven below zero,
    zero itself, eight above, both ends included."""
    from statistics import NormalDist

    ends = 1 - 0.5 * (1 / 30 + 1 / 32)  # the outermost quantile; beyond it lies half a step of either side
    above = [NormalDist().inv_cdf(q) for q in np.linspace(0.5, ends, 9)[1:]]
    below = [NormalDist().inv_cdf(q) for q in np.linspace(0.5, ends, 8)[1:]]
    return np.array(sorted([-x / below[-1] for x in below] + [0.0] + [x / above[-1] for x in above]))


CODE = normal_levels()


def quantize4(w: np.ndarray, block: int = 64) -> tuple[np.ndarray, np.ndarray, tuple[int, ...]]:
    """Codes (two to a byte) and one scale for each block of weights."""
    flat = np.pad(w.reshape(-1).astype(float), (0, -w.size % block)).reshape(-1, block)
    scale = np.maximum(np.abs(flat).max(1, keepdims=True), 1e-12)
    code = np.abs((flat / scale)[..., None] - CODE).argmin(-1).astype(np.uint8).reshape(-1)
    return (code[::2] << 4) | code[1::2], scale[:, 0].astype(np.float32), w.shape


def dequantize4(packed: np.ndarray, scale: np.ndarray, shape: tuple[int, ...], block: int = 64) -> np.ndarray:
    code = np.stack([packed >> 4, packed & 15], 1).reshape(-1, block)
    return (CODE[code] * scale[:, None]).reshape(-1)[: math.prod(shape)].reshape(shape)


@dataclass
class Adapter:
    """W = base + (alpha / r) B A; only A and B are trained, B starts at zero."""

    base: np.ndarray
    r: int = 64
    alpha: float = 128.0
    seed: int = 42
    a: np.ndarray = field(init=False)
    b: np.ndarray = field(init=False)

    def __post_init__(self) -> None:
        rng = np.random.default_rng(self.seed)
        self.a = rng.normal(0, 1 / math.sqrt(self.base.shape[1]), (self.r, self.base.shape[1]))
        self.b = np.zeros((self.base.shape[0], self.r))

    def merge(self) -> np.ndarray:
        return self.base + self.alpha / self.r * self.b @ self.a

    def n_trainable(self) -> int:
        return self.a.size + self.b.size

    def loss_grad(self, x: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        """Sum of -log softmax(W x)[y] over rows and its gradients in A and B."""
        z = x @ self.merge().T
        z -= z.max(1, keepdims=True)
        p = np.exp(z)
        p /= p.sum(1, keepdims=True)
        loss = float(-np.log(p[np.arange(len(y)), y] + 1e-300).sum())
        p[np.arange(len(y)), y] -= 1
        g = p.T @ x * (self.alpha / self.r)
        return loss, self.b.T @ g, g @ self.a.T


@dataclass
class AdamW:
    lr: float = 1e-4
    wd: float = 0.01
    betas: tuple[float, float] = (0.9, 0.999)
    t: int = 0
    state: dict = field(default_factory=dict)

    def step(self, name: str, value: np.ndarray, grad: np.ndarray) -> np.ndarray:
        m, v = self.state.get(name, (np.zeros_like(value), np.zeros_like(value)))
        m, v = self.betas[0] * m + (1 - self.betas[0]) * grad, self.betas[1] * v + (1 - self.betas[1]) * grad**2
        self.state[name] = m, v
        mh, vh = m / (1 - self.betas[0] ** self.t), v / (1 - self.betas[1] ** self.t)
        return value - self.lr * (mh / (np.sqrt(vh) + 1e-8) + self.wd * value)

    def step_rows(self, name: str, value: np.ndarray, rows: np.ndarray, grad: np.ndarray) -> None:
        """One step of some rows of ``value``, in place; the moments of other rows wait."""
        m, v = self.state.setdefault(name, (np.zeros_like(value), np.zeros_like(value)))
        m[rows] = self.betas[0] * m[rows] + (1 - self.betas[0]) * grad
        v[rows] = self.betas[1] * v[rows] + (1 - self.betas[1]) * grad**2
        mh, vh = m[rows] / (1 - self.betas[0] ** self.t), v[rows] / (1 - self.betas[1] ** self.t)
        value[rows] -= self.lr * (mh / (np.sqrt(vh) + 1e-8) + self.wd * value[rows])


def batches(df: DataFrame, size: int, epoch: int, key: str, seed: int = 42) -> DataFrame:
    """``df`` with batch: hash-shuffled anew each epoch, numbered without one task for all rows.

    A row's place is its rank in its hash bucket after the sizes of earlier buckets."""
    h = F.md5(F.concat_ws("|", F.lit(f"{seed}|{epoch}"), F.col(key).cast("string")))
    keyed = df.withColumn("_h", h).withColumn("_b", F.substring("_h", 1, 2))
    sizes = keyed.groupBy("_b").agg(F.count("*").alias("_n"))  # 256 rows at most
    before = sizes.select("_b", F.coalesce(F.sum("_n").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_o"))
    placed = keyed.join(F.broadcast(before), "_b").withColumn("_r", F.col("_o") + F.row_number().over(Window.partitionBy("_b").orderBy("_h", key)) - 1)
    return placed.withColumn("batch", F.floor(F.col("_r") / size)).drop("_h", "_b", "_o", "_r")


def grad_step(df: DataFrame, model: Adapter, x: str = "x", y: str = "y") -> tuple[float, int, np.ndarray, np.ndarray]:
    """Loss, rows and gradients over a DataFrame: partial sums by partition, one row each, summed in
    a second stage before the driver gets them."""
    shared = df.sparkSession.sparkContext.broadcast(model)

    def part(frames):
        m = shared.value
        loss, n, ga, gb = 0.0, 0, np.zeros_like(m.a), np.zeros_like(m.b)
        for f in frames:
            if len(f):
                one = m.loss_grad(np.stack(f[x].to_numpy()).astype(float), f[y].to_numpy().astype(int))
                loss, n, ga, gb = loss + one[0], n + len(f), ga + one[1], gb + one[2]
        yield pd.DataFrame({"k": [TaskContext.get().partitionId() % 16], "loss": [loss], "n": [n], "a": [ga.tobytes()], "b": [gb.tobytes()]})

    def total(f: pd.DataFrame) -> pd.DataFrame:
        add = lambda c: sum(np.frombuffer(v) for v in f[c]).tobytes()
        return pd.DataFrame({"k": [0], "loss": [f["loss"].sum()], "n": [f["n"].sum()], "a": [add("a")], "b": [add("b")]})

    kind = "k long, loss double, n long, a binary, b binary"
    rows = df.select(x, y).mapInPandas(part, kind).groupBy("k").applyInPandas(total, kind).collect()  # 16 rows at most
    ga, gb = (sum((np.frombuffer(r[c]) for r in rows), np.zeros(s.size)).reshape(s.shape) for c, s in (("a", model.a), ("b", model.b)))
    return sum(r.loss for r in rows), sum(r.n for r in rows), ga, gb


@dataclass
class EarlyStop:
    """The rule of ``metrics.early_stop``, one evaluation at a time: a loss counts as better if it
    is under the least of all earlier ones by more than ``tol``."""

    patience: int = 8
    tol: float = 1e-3
    least: float = math.inf
    wait: int = 0

    def better(self, loss: float) -> bool:
        gained = not math.isnan(loss) and loss < self.least - self.tol
        if not math.isnan(loss):
            self.least = min(self.least, loss)
        self.wait = 0 if gained else self.wait + 1
        return gained

    @property
    def done(self) -> bool:
        return self.wait >= self.patience


def train(df: DataFrame, valid: DataFrame, model: Adapter, key: str, size: int = 6, epochs: int = 2, lr: float = 1e-4, patience: int = 8, tol: float = 1e-3, every: int = 1) -> list[dict]:
    """Trains the adapter; the curve has an entry for each evaluation on ``valid`` (ID and OOD
    pooled); the best state is put back at the end."""
    opt, curve, best, rule, step = AdamW(lr), [], None, EarlyStop(patience, tol), 0
    for epoch in range(epochs):
        # one pass deals the epoch's batches to partitions, so a step reads its batch, not the set
        shuffled = batches(df, size, epoch, key).persist()
        n_rows = shuffled.count()
        for b in range(math.ceil(n_rows / size)):
            loss, n, ga, gb = grad_step(shuffled.where(F.col("batch") == b), model)
            step += 1
            opt.t = step
            model.a, model.b = opt.step("a", model.a, ga / max(n, 1)), opt.step("b", model.b, gb / max(n, 1))
            if step % every:
                continue
            v_loss, v_n, _, _ = grad_step(valid, model)
            v = v_loss / max(v_n, 1)
            curve.append({"step": step, "epoch": epoch + min(1.0, (b + 1) * size / max(1, n_rows)), "train": loss / max(n, 1), "loss": v})
            if rule.better(v):
                best = model.a.copy(), model.b.copy()
            if rule.done:
                break
        shuffled.unpersist()
        if rule.done:
            break
    if best is not None:
        model.a, model.b = best
    return curve


class Greedy:
    """Decodes from trigram counts over a closed vocabulary: the most frequent next token, shorter
    contexts where a longer one is new, to the end mark or the cap."""

    END = "</s>"

    def __init__(self, texts: list[str]):
        self.next: dict[tuple[str, ...], dict[str, int]] = {}
        for t in texts:
            toks = [*t.split(" "), self.END]
            for i, w in enumerate(toks):
                for k in range(4):
                    if i >= k:
                        at = self.next.setdefault(tuple(toks[i - k : i]), {})
                        at[w] = at.get(w, 0) + 1

    def decode(self, prompt: str, max_out: int = 1500) -> str:
        toks, made = prompt.split(" "), []
        while len(made) < max_out:
            ctx = next(c for k in range(3, -1, -1) if (c := tuple((toks + made)[-k:] if k else ())) in self.next)
            w = min(self.next[ctx].items(), key=lambda x: (-x[1], x[0]))[0]
            if w == self.END:
                break
            made.append(w)
        return " ".join(made)
