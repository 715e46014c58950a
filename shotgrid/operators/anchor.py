"""Learned pixel prediction: context patches as small point clouds, a point network with anchor heads, and its exact integer form.

Training runs in floats; coding runs on a frozen copy whose weights and activations are integers held in float64. Every
dot product stays below 2**53, so its value does not depend on the order of additions or on how many pixels are computed
together: encoder and decoder get the same predictions whatever their batches are."""

from __future__ import annotations

import hashlib
import pickle
from dataclasses import dataclass, field, replace

import numpy as np

ONE = 12  # bits of fraction of activations
WEIGHT = 11  # bits of fraction of frozen weights
REACH = 75.0  # metres; ranges are divided by it
GAIN = 8.0  # relative ranges are multiplied by it, so that near neighbours differ visibly
BINS = 75
LIMIT = float(1 << 20)
#: Outputs per point or patch of each kind of head.
HEADS = ("anchor", "mse", "mae", "multibin", "cnn")


@dataclass(frozen=True)
class NetSpec:
    """context: rows and columns of the patch. angles: False gives offsets in rows and columns. temporal: none, image or knn;
    points: previous points per pixel (knn). az, el: angle of each column and row in microradians."""

    context: tuple[int, int] = (10, 10)
    head: str = "anchor"
    width: float = 1.0
    angles: bool = True
    temporal: str = "none"
    points: int = 100
    az: tuple[int, ...] = ()
    el: tuple[int, ...] = ()

    @property
    def offsets(self) -> tuple[np.ndarray, np.ndarray]:
        h, w = self.context
        di, dj = np.divmod(np.arange(1, h * w), w)
        return di, dj

    @property
    def inputs(self) -> int:
        return 3 if self.temporal == "none" else 4


def patch(spec: NetSpec, code: np.ndarray, valid: np.ndarray, b: np.ndarray, i: np.ndarray, j: np.ndarray, i0=0, j0=0) -> dict:
    """Context of pixels (b, i, j) of images code[b]: values, mask and integer angles of every offset; outside is void (zero padding).

    i0, j0: row and column of the images' first pixel, which the angles are looked up with."""
    di, dj = spec.offsets
    r, c = i[:, None] - di, j[:, None] - dj
    inner = (r >= 0) & (c >= 0)
    r, c = np.maximum(r, 0), np.maximum(c, 0)
    ok = inner & valid[b[:, None], r, c]
    value = np.where(ok, code[b[:, None], r, c], 0)
    return {"value": value, "ok": ok, **angles(spec, i, j, r, c, i0, j0), "time": np.zeros(ok.shape, np.int64)}


def angles(spec: NetSpec, i, j, r, c, i0=0, j0=0) -> dict:
    shift = lambda x: x[:, None] if isinstance(x, np.ndarray) else x
    if spec.angles and spec.az:
        az, el = np.array(spec.az, np.int64), np.array(spec.el, np.int64)
        return {"daz": az[c + shift(j0)] - az[j + j0][:, None], "del": el[r + shift(i0)] - el[i + i0][:, None]}
    return {"daz": (c - j[:, None]) * 20_000, "del": (r - i[:, None]) * 10_000}


def joined(a: dict, b: dict) -> dict:
    return {k: np.concatenate([a[k], b[k]], 1) for k in a}


def features(p: dict, d: float | np.ndarray, inputs: int) -> tuple[np.ndarray, np.ndarray]:
    """Integer features (scaled by 2**ONE) of every context point and the mean valid code of each patch; all integer arithmetic."""
    n = np.maximum(p["ok"].sum(1), 1)
    mean = p["value"].sum(1) // n
    step = np.round(np.asarray(d) / REACH * GAIN * (1 << (ONE + 16))).astype(np.int64)
    near = ((p["value"] - mean[:, None]) * (step[:, None] if step.ndim else step)) >> 16
    cols = [p["daz"] * (1 << ONE) // 250_000, p["del"] * (1 << ONE) // 100_000, near, p["time"] << ONE][:inputs]
    x = np.clip(np.stack(cols, 2), -(1 << 17), 1 << 17).astype(np.float64)
    x[~p["ok"]] = 0
    return x, mean


class Net:
    """Shared point layers, max pool over the valid points, local and global features joined, and the head's layers."""

    def __init__(self, spec: NetSpec, seed: int = 0):
        self.spec, rng = spec, np.random.default_rng(seed)
        c = lambda n: max(4, round(n * spec.width))
        a, mid, top, h1, h2 = c(32), c(64), c(512), c(128), c(64)
        self.shape = {"p1": (spec.inputs, a), "p2": (a, a), "p3": (a, a), "p4": (a, mid), "p5": (mid, top)}
        if spec.head == "anchor":
            for n in ("s", "r"):
                self.shape |= {f"{n}1l": (a, h1), f"{n}1g": (top, h1), f"{n}2": (h1, h2), f"{n}3": (h2, 1)}
        else:
            self.shape |= {"g1": (top, h1), "g2": (h1, h2), "g3": (h2, 2 * BINS if spec.head == "multibin" else 1)}
        self.w = {n: rng.normal(0, np.sqrt(2 / i), (i, o)) for n, (i, o) in self.shape.items()}
        for n in ("r3", "g3"):
            if n in self.w:
                self.w[n] *= 0.1
        self.b = {n: np.zeros(o) for n, (i, o) in self.shape.items()}
        self.frozen = False

    # A frozen layer floors the scaled sum; a trained one is a plain affine map. Both end in the same rectifier.
    def _lin(self, x, n, relu=True, add=None):
        y = x @ self.w[n] + (self.b[n] if not n.endswith("l") else 0)
        if add is not None:
            y = y + add
        if self.frozen:
            y = np.clip(np.floor(y / (1 << WEIGHT)), -LIMIT, LIMIT)
        return np.maximum(y, 0) if relu else y

    def forward(self, x: np.ndarray, ok: np.ndarray, keep: bool = False) -> dict:
        """Scores and residuals of every point (anchor head), or the head's outputs of every patch."""
        t: dict = {"x": x, "ok": ok}
        t["a1"] = self._lin(x, "p1")
        t["a2"] = self._lin(t["a1"], "p2")
        t["a3"] = self._lin(t["a2"], "p3")
        t["a4"] = self._lin(t["a3"], "p4")
        t["a5"] = self._lin(t["a4"], "p5")
        masked = np.where(ok[:, :, None], t["a5"], -1.0)
        t["arg"] = masked.argmax(1)
        t["g"] = np.maximum(np.take_along_axis(masked, t["arg"][:, None, :], 1)[:, 0, :], 0)
        if self.spec.head == "anchor":
            for n in ("s", "r"):
                whole = t["g"] @ self.w[f"{n}1g"] + self.b[f"{n}1g"]
                t[f"{n}h1"] = self._lin(t["a2"], f"{n}1l", add=whole[:, None, :])
                t[f"{n}h2"] = self._lin(t[f"{n}h1"], f"{n}2")
                t[n] = self._lin(t[f"{n}h2"], f"{n}3", relu=False)[:, :, 0]
        else:
            t["h1"] = self._lin(t["g"], "g1")
            t["h2"] = self._lin(t["h1"], "g2")
            t["out"] = self._lin(t["h2"], "g3", relu=False)
        return t if keep else {k: t[k] for k in ("s", "r", "out") if k in t}

    def loss(self, batch: dict, gamma: float = 0.01) -> tuple[float, dict]:
        """Mean loss of a batch (see samples_of) and its gradient by layer; patches without context don't count."""
        x, ok = batch["x"] / (1 << ONE), batch["ok"]
        t, P = self.forward(x, ok, keep=True), len(x)
        live = ok.any(1)
        n = max(1, int(live.sum()))
        grads: dict = {}

        def back(name, inp, out, g, relu=True):
            g = g * (out > 0) if relu else g
            flat = lambda v: v.reshape(-1, v.shape[-1])
            grads[name] = (flat(inp).T @ flat(g), flat(g).sum(0))
            return g @ self.w[name].T

        if self.spec.head == "anchor":
            y, rows = batch["label"], np.arange(P)
            s = np.where(ok, t["s"], -1e9)
            e = np.exp(s - s.max(1, keepdims=True))
            soft = e / e.sum(1, keepdims=True)
            miss = t["r"][rows, y] - batch["gap"]
            value = float((gamma * -np.log(soft[rows, y] + 1e-12) + np.abs(miss))[live].sum() / n)
            gs = soft.copy()
            gs[rows, y] -= 1
            gs *= gamma * live[:, None] / n * ok
            gr = np.zeros_like(t["r"])
            gr[rows, y] = np.sign(miss) * live / n
            da2, dg = np.zeros_like(t["a2"]), np.zeros_like(t["g"])
            for k, g in (("s", gs), ("r", gr)):
                g = back(f"{k}3", t[f"{k}h2"], None, g[:, :, None], relu=False)
                g = back(f"{k}2", t[f"{k}h1"], t[f"{k}h2"], g) * (t[f"{k}h1"] > 0)
                grads[f"{k}1l"] = (t["a2"].reshape(-1, t["a2"].shape[-1]).T @ g.reshape(-1, g.shape[-1]), np.zeros(g.shape[-1]))
                each = g.sum(1)
                grads[f"{k}1g"] = (t["g"].T @ each, each.sum(0))
                da2 += g @ self.w[f"{k}1l"].T
                dg += each @ self.w[f"{k}1g"].T
        else:
            out, target = t["out"], batch["whole"]
            g = np.zeros_like(out)
            if self.spec.head == "multibin":
                rows, y = np.arange(P), batch["bin"]
                e = np.exp(out[:, :BINS] - out[:, :BINS].max(1, keepdims=True))
                soft = e / e.sum(1, keepdims=True)
                miss = out[rows, BINS + y] - batch["inbin"]
                value = float((gamma * -np.log(soft[rows, y] + 1e-12) + np.abs(miss))[live].sum() / n)
                g[:, :BINS] = soft * gamma
                g[rows, y] -= gamma
                g[rows, BINS + y] = np.sign(miss)
            else:
                miss = out[:, 0] - target
                value = float((miss * miss if self.spec.head == "mse" else np.abs(miss))[live].sum() / n)
                g[:, 0] = 2 * miss if self.spec.head == "mse" else np.sign(miss)
            g *= live[:, None] / n
            g = back("g3", t["h2"], None, g, relu=False)
            g = back("g2", t["h1"], t["h2"], g)
            dg, da2 = back("g1", t["g"], t["h1"], g), np.zeros_like(t["a2"])
        da5 = np.zeros_like(t["a5"])
        np.put_along_axis(da5, t["arg"][:, None, :], (dg * (t["g"] > 0))[:, None, :], 1)
        g = back("p5", t["a4"], t["a5"], da5)
        g = back("p4", t["a3"], t["a4"], g)
        g = back("p3", t["a2"], t["a3"], g) + da2
        g = back("p2", t["a1"], t["a2"], g)
        back("p1", t["x"], t["a1"], g)
        return value, grads

    def freeze(self) -> Net:
        """The integer copy: weights rounded to WEIGHT fraction bits, biases to the scale of the sums."""
        out = Net.__new__(type(self))
        out.spec, out.shape, out.frozen = self.spec, self.shape, True
        out.w = {n: np.clip(np.round(v * (1 << WEIGHT)), -(1 << 15), 1 << 15) for n, v in self.w.items()}
        out.b = {n: np.clip(np.round(v * (1 << (WEIGHT + ONE))), -(2.0**40), 2.0**40) for n, v in self.b.items()}
        return out

    @property
    def model_id(self) -> str:
        """Hash of the frozen weights and the spec: a container names the model that wrote it."""
        raw = b"".join(self.w[n].astype("<f8").tobytes() + self.b[n].astype("<f8").tobytes() for n in sorted(self.w))
        return hashlib.sha256(raw + repr(self.spec).encode()).hexdigest()[:16]

    def predict(self, p: dict, d: float) -> np.ndarray:
        """Predicted codes of pixels from their contexts (frozen network): the best anchor's code plus its residual; 0 without context."""
        assert self.frozen, "coding needs the frozen network"
        out = np.zeros(len(p["ok"]), np.int64)
        scale = round(REACH / GAIN / d * 256)
        moved = lambda r: (r.astype(np.int64) * scale + (1 << (ONE + 7))) >> (ONE + 8)
        most = max(16, int(3e6 // (p["ok"].shape[1] * max(s[1] for s in self.shape.values()))))
        for a in range(0, len(out), most):
            q = {k: v[a : a + most] for k, v in p.items()}
            x, mean = features(q, d, self.spec.inputs)
            t = self.forward(x, q["ok"])
            rows = np.arange(len(mean))
            if self.spec.head == "anchor":
                best = np.where(q["ok"], t["s"], -(2.0**60)).argmax(1)
                got = q["value"][rows, best] + moved(t["r"][rows, best])
            elif self.spec.head == "multibin":
                best = t["out"][:, :BINS].argmax(1)
                metre = (best * round(1 / d * 4096) + (np.clip(t["out"][rows, BINS + best], 0, 1 << ONE).astype(np.int64) * round(1 / d * 4096) >> ONE)) >> 12
                got = metre
            else:
                got = mean + moved(t["out"][:, 0])
            out[a : a + most] = np.where(q["ok"].any(1), np.maximum(got, 0), 0)
        return out

    def dumps(self) -> bytes:
        return pickle.dumps((self.spec, self.shape, self.w, self.b, self.frozen))

    @classmethod
    def loads(cls, raw: bytes) -> Net:
        """Only from the driver's own broadcast: pickles are not read from containers."""
        out = Net.__new__(ConvNet if pickle.loads(raw)[0].head == "cnn" else Net)
        out.spec, out.shape, out.w, out.b, out.frozen = pickle.loads(raw)
        return out


class ConvNet(Net):
    """Image baseline: 3 x 3 convolutions on the patch of relative ranges, residual blocks, one output from the bottom right pixel."""

    BLOCKS = 5

    def __init__(self, spec: NetSpec, seed: int = 0):
        self.spec, rng = spec, np.random.default_rng(seed)
        c = lambda n: max(4, round(n * spec.width))
        a, m = c(64), c(32)
        self.shape = {"c0": (18, a), "c1": (9 * a, m)} | {f"b{i}{k}": (9 * m, m) for i in range(self.BLOCKS) for k in "xy"} | {"g3": (m, 1)}
        self.w = {n: rng.normal(0, np.sqrt(2 / i) * (0.3 if n.endswith("y") or n == "g3" else 1), (i, o)) for n, (i, o) in self.shape.items()}
        self.b = {n: np.zeros(o) for n, (i, o) in self.shape.items()}
        self.frozen = False

    def _columns(self, x: np.ndarray) -> np.ndarray:
        """im2col of 3 x 3 neighbourhoods with zero padding: (P, h, w, 9 c)."""
        p = np.pad(x, ((0, 0), (1, 1), (1, 1), (0, 0)))
        h, w = x.shape[1:3]
        return np.concatenate([p[:, a : a + h, b : b + w] for a in range(3) for b in range(3)], 3)

    def _spread(self, g: np.ndarray, c: int) -> np.ndarray:
        h, w = g.shape[1:3]
        p = np.zeros((len(g), h + 2, w + 2, c))
        for n, (a, b) in enumerate((a, b) for a in range(3) for b in range(3)):
            p[:, a : a + h, b : b + w] += g[..., n * c : (n + 1) * c]
        return p[:, 1:-1, 1:-1]

    def forward(self, x: np.ndarray, ok: np.ndarray, keep: bool = False) -> dict:
        h, w = self.spec.context
        grid = np.zeros((len(x), h * w, 2))
        grid[:, 1:, 0], grid[:, 1:, 1] = x[:, :, 2], ok * (float(1 << ONE) if self.frozen else 1.0)
        grid = grid[:, ::-1].reshape(len(x), h, w, 2)  # offset 0 is the bottom right pixel
        t = {"v0": self._columns(grid)}
        at = self._lin(t["v0"], "c0")
        t["u0"], t["v1"] = at, self._columns(at)
        at = t["u1"] = self._lin(t["v1"], "c1")
        for i in range(self.BLOCKS):
            t[f"v{i}x"] = self._columns(at)
            mid = t[f"u{i}x"] = self._lin(t[f"v{i}x"], f"b{i}x")
            t[f"v{i}y"] = self._columns(mid)
            at = t[f"u{i}y"] = np.maximum(at + self._lin(t[f"v{i}y"], f"b{i}y", relu=False), 0)
        t["last"] = at[:, -1, -1]
        t["out"] = self._lin(t["last"], "g3", relu=False)
        return t if keep else {"out": t["out"]}

    def loss(self, batch: dict, gamma: float = 0.01) -> tuple[float, dict]:
        t = self.forward(batch["x"] / (1 << ONE), batch["ok"], keep=True)
        live = batch["ok"].any(1)
        n, miss, grads = max(1, int(live.sum())), t["out"][:, 0] - batch["whole"], {}
        flat = lambda v: v.reshape(-1, v.shape[-1])

        def back(name, cols, g):
            grads[name] = (flat(cols).T @ flat(g), flat(g).sum(0))
            return g @ self.w[name].T

        g = back("g3", t["last"], (np.sign(miss) * live / n)[:, None])
        at = np.zeros_like(t["u1"])
        at[:, -1, -1] = g
        for i in reversed(range(self.BLOCKS)):
            at = at * (t[f"u{i}y"] > 0)
            m = at.shape[-1]
            g = self._spread(back(f"b{i}y", t[f"v{i}y"], at), m) * (t[f"u{i}x"] > 0)
            at = at + self._spread(back(f"b{i}x", t[f"v{i}x"], g), m)
        g = self._spread(back("c1", t["v1"], at * (t["u1"] > 0)), t["u0"].shape[-1]) * (t["u0"] > 0)
        back("c0", t["v0"], g)
        return float(np.abs(miss)[live].sum() / n), grads


def build(spec: NetSpec, seed: int = 0) -> Net:
    return (ConvNet if spec.head == "cnn" else Net)(spec, seed)


def samples_of(p: dict, target: np.ndarray, d: float | np.ndarray, spec: NetSpec) -> dict:
    """Training batch from contexts (values are codes of precision d) and full-precision targets in metres.

    The label is the anchor nearest in value; ties go to the one closest in angle."""
    x, mean = features(p, d, spec.inputs)
    wide = np.asarray(d)[:, None] if np.ndim(d) else d
    metres = p["value"] * wide
    near = np.abs(metres - target[:, None]) + 1e-9 * (np.abs(p["daz"]) + np.abs(p["del"]))
    label = np.where(p["ok"], near, np.inf).argmin(1)
    unit = REACH / GAIN
    rows = np.arange(len(target))
    bins = np.clip(target.astype(np.int64), 0, BINS - 1)
    return {"x": x, "ok": p["ok"], "label": label, "gap": (target - metres[rows, label]) / unit, "whole": (target - mean * np.asarray(d)) / unit, "bin": bins, "inbin": target - bins}


@dataclass
class Adam:
    """Adam with a step-wise decay: the rate falls tenfold at every milestone."""

    rate: float = 5e-5
    milestones: tuple[int, ...] = (1_500_000, 3_000_000)
    m: dict = field(default_factory=dict)
    v: dict = field(default_factory=dict)
    t: int = 0

    def step(self, net: Net, grads: dict) -> None:
        self.t += 1
        rate = self.rate * 0.1 ** sum(self.t >= s for s in self.milestones)
        for n, pair in grads.items():
            for store, g, k in ((net.w, pair[0], (n, 0)), (net.b, pair[1], (n, 1))):
                m = self.m[k] = 0.9 * self.m.get(k, 0) + 0.1 * g
                v = self.v[k] = 0.999 * self.v.get(k, 0) + 0.001 * g * g
                store[n] = store[n] - rate * (m / (1 - 0.9**self.t)) / (np.sqrt(v / (1 - 0.999**self.t)) + 1e-8)


def fit(spec: NetSpec, draw, steps: int, batch: int = 128, rate: float = 5e-5, milestones: tuple[int, ...] = (1_500_000, 3_000_000), gamma: float = 0.01, seed: int = 0) -> tuple[Net, list[float]]:
    """Trains a network; draw(n, rng) gives a batch of n samples. Returns it with the loss of every step."""
    net, opt, rng, history = build(spec, seed), Adam(rate, milestones), np.random.default_rng(seed), []
    for _ in range(steps):
        value, grads = net.loss(draw(batch, rng), gamma)
        opt.step(net, grads)
        history.append(value)
    return net, history


def wavefront(net: Net, delta: np.ndarray, valid: np.ndarray, d: float, i0: np.ndarray, j0: np.ndarray, extra=None) -> np.ndarray:
    """Codes of many blocks from their deltas: all pixels of an anti-diagonal of all blocks at a time.

    The context of (i, j) has rows up to i and columns up to j without the pixel itself, so smaller i + j only. extra(b, i, j,
    code) adds context points from elsewhere (the previous frame)."""
    code = np.zeros_like(delta)
    h, w = delta.shape[1:]
    for s in range(h + w - 1):
        lo, hi = max(0, s - w + 1), min(h - 1, s)
        ii = np.arange(lo, hi + 1)
        b, k = np.nonzero(valid[:, ii, s - ii])
        if len(b):
            i, j = ii[k], s - ii[k]
            p = patch(net.spec, code, valid, b, i, j, i0[b], j0[b])
            if extra is not None:
                p = joined(p, extra(b, i, j, code))
            code[b, i, j] = net.predict(p, d) + delta[b, i, j]
    return code


def spec_for(spec: NetSpec, az: np.ndarray, el: np.ndarray) -> NetSpec:
    return replace(spec, az=tuple(int(x) for x in np.round(az * 1e6)), el=tuple(int(x) for x in np.round(el * 1e6)))
