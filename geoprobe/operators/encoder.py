"""A small image-text encoder in numpy, with gradients for every adaptation strategy.

Image side: patches, a rectified linear embedding with positions, transformer blocks (attention and perceptron, each
after a normalisation), a final normalisation, mean pooling and a projection to unit length. Text side: hashed words,
projected. Heads: cosine with the class texts (scaled), scale and bias of those scores (of each class, of all, or of the text features'
dimensions), or linear."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
import xxhash

from .rasters import SIDE, preprocessed

PATCH, WIDTH, HIDDEN, OUT, TEXT_BINS, BLOCKS = 7, 32, 64, 64, 2048, 2
TOKENS = (SIDE // PATCH) ** 2
ROOT = WIDTH**-0.5
#: Scale of cosine scores before the softmax.
HEAT = 20.0
#: Tensors of a block, named `<number>.<name>`.
BLOCK = ("g1", "b1", "wq", "wk", "wv", "wo", "g2", "b2", "w1", "c1", "w2", "c2")
FINAL = ("gf", "bf")
EMBED = ("we", "be", "pos")
ADAPTED = {"attention": ("wq", "wk", "wv", "wo"), "perceptron": ("w1", "w2")}
STRATEGIES = ("zero_shot", "text_score", "linear", "last_block", "low_rank", "full")
FROZEN = ("zero_shot", "text_score", "linear")
SHAPES = ("per_class", "scalar", "per_dim")


def depth(w: dict) -> int:
    """How many blocks the weights have."""
    return sum(name.endswith(".wq") for name in w)


def block_names(i: int) -> tuple[str, ...]:
    return tuple(f"{i}.{n}" for n in BLOCK)


def initial(seed: int = 42, channels: int = 3, blocks: int = BLOCKS) -> dict[str, np.ndarray]:
    """Random encoder weights; the projection is set by alignment."""
    rng = np.random.default_rng(seed)
    normal = lambda *shape, scale: (rng.standard_normal(shape) * scale).astype(np.float32)
    size = PATCH * PATCH * channels
    w = {"we": normal(size, WIDTH, scale=size**-0.5), "be": normal(WIDTH, scale=0.3), "pos": normal(TOKENS, WIDTH, scale=0.05)}
    for i in range(blocks):
        for k, a, b in (("wq", WIDTH, WIDTH), ("wk", WIDTH, WIDTH), ("wv", WIDTH, WIDTH), ("wo", WIDTH, WIDTH), ("w1", WIDTH, HIDDEN), ("w2", HIDDEN, WIDTH)):
            w[f"{i}.{k}"] = normal(a, b, scale=0.5 * a**-0.5)
        w |= {f"{i}.{k}": np.zeros(n, np.float32) for k, n in (("b1", WIDTH), ("b2", WIDTH), ("c1", HIDDEN), ("c2", WIDTH))}
        w |= {f"{i}.{k}": np.ones(WIDTH, np.float32) for k in ("g1", "g2")}
    w |= {"gf": np.ones(WIDTH, np.float32), "bf": np.zeros(WIDTH, np.float32), "proj": normal(WIDTH, OUT, scale=WIDTH**-0.5)}
    return w


def patches(rasters: np.ndarray) -> np.ndarray:
    """(images, tokens, values) of preprocessed rasters."""
    n, per = len(rasters), SIDE // PATCH
    x = preprocessed(rasters.astype(np.float32)).reshape(n, per, PATCH, per, PATCH, -1)
    return x.transpose(0, 1, 3, 2, 4, 5).reshape(n, per * per, -1)


def _norm(x, g, b):
    h = x - x.mean(axis=-1, keepdims=True)
    s = 1 / np.sqrt((h * h).mean(axis=-1, keepdims=True) + 1e-5)
    h *= s
    return h * g + b, (h, s)


def _norm_back(dy, g, kept):
    h, s = kept
    dh = dy * g
    axes = tuple(range(dy.ndim - 1))
    return s * (dh - dh.mean(axis=-1, keepdims=True) - h * (dh * h).mean(axis=-1, keepdims=True)), (dy * h).sum(axis=axes), dy.sum(axis=axes)


def _flat(a, b):
    return a.reshape(-1, a.shape[-1]).T @ b.reshape(-1, b.shape[-1])


def _linear_back(w: dict, name: str, x: np.ndarray, d: np.ndarray, g: dict) -> np.ndarray:
    """Gradients of a matrix (or of each example's own matrix) and of x."""
    g[name] = _flat(x, d) if w[name].ndim == 2 else x.transpose(0, 2, 1) @ d
    return d @ w[name].swapaxes(-1, -2)


def embedded(w: dict, tokens: np.ndarray, k: dict | None = None) -> np.ndarray:
    """What the first block reads."""
    pre = tokens @ w["we"] + w["be"]
    live = pre > 0
    if k is not None:
        k |= {"in": tokens, "live": live}
    return pre * live + w["pos"]


def _block(w: dict, i: int, x: np.ndarray) -> tuple[np.ndarray, dict]:
    k: dict = {}
    at = lambda name: f"{i}.{name}"
    k["a"], k["n1"] = _norm(x, w[at("g1")], w[at("b1")])
    q, key, v = (k["a"] @ w[at(n)] for n in ("wq", "wk", "wv"))
    s = q @ key.transpose(0, 2, 1) * ROOT
    s = np.exp(s - s.max(axis=-1, keepdims=True))
    s /= s.sum(axis=-1, keepdims=True)
    k |= {"q": q, "key": key, "v": v, "s": s, "mix": s @ v}
    x = x + k["mix"] @ w[at("wo")]
    k["m"], k["n2"] = _norm(x, w[at("g2")], w[at("b2")])
    k["h"] = np.maximum(k["m"] @ w[at("w1")] + w[at("c1")], 0)
    return x + k["h"] @ w[at("w2")] + w[at("c2")], k


def _block_back(w: dict, i: int, k: dict, dx: np.ndarray, g: dict) -> np.ndarray:
    at = lambda name: f"{i}.{name}"
    g[at("c2")] = dx.sum(axis=(0, 1))
    dh = _linear_back(w, at("w2"), k["h"], dx, g) * (k["h"] > 0)
    g[at("c1")] = dh.sum(axis=(0, 1))
    dn, g[at("g2")], g[at("b2")] = _norm_back(_linear_back(w, at("w1"), k["m"], dh, g), w[at("g2")], k["n2"])
    dx = dx + dn
    dmix = _linear_back(w, at("wo"), k["mix"], dx, g)
    ds = dmix @ k["v"].transpose(0, 2, 1)
    dv = k["s"].transpose(0, 2, 1) @ dmix
    ds = k["s"] * (ds - (ds * k["s"]).sum(axis=-1, keepdims=True)) * ROOT
    dq, dk = ds @ k["key"], ds.transpose(0, 2, 1) @ k["q"]
    da = sum(_linear_back(w, at(n), k["a"], d, g) for n, d in (("wq", dq), ("wk", dk), ("wv", dv)))
    dn, g[at("g1")], g[at("b1")] = _norm_back(da, w[at("g1")], k["n1"])
    return dx + dn


def through(w: dict, x: np.ndarray, first: int, last: int) -> tuple[np.ndarray, list[dict]]:
    """Blocks `first` to `last` (exclusive) applied to what block `first` reads."""
    kept = []
    for i in range(first, last):
        x, k = _block(w, i, x)
        kept.append(k)
    return x, kept


def read_out(w: dict, x: np.ndarray) -> tuple[np.ndarray, dict]:
    """Unit features of what the last block gives."""
    k: dict = {}
    f, k["nf"] = _norm(x, w["gf"], w["bf"])
    k["pool"] = f.mean(axis=1)
    z = k["pool"] @ w["proj"]
    k["len"] = np.linalg.norm(z, axis=1, keepdims=True) + 1e-8
    k["feature"] = z / k["len"]
    return k["feature"], k


def forward(w: dict, tokens: np.ndarray, hidden: np.ndarray | None = None, first: int = 0) -> tuple[np.ndarray, dict]:
    """Unit features and what the backward pass needs; from what block `first` reads if `hidden` is given. A matrix may have
    one form for all examples, or one for each (a leading axis)."""
    k: dict = {"first": first}
    x = embedded(w, tokens, k) if hidden is None else hidden
    x, k["blocks"] = through(w, x, first, depth(w))
    feature, last = read_out(w, x)
    return feature, k | last


def backward(w: dict, k: dict, dfeature: np.ndarray) -> dict[str, np.ndarray]:
    """Gradients of all that the forward pass went through."""
    g: dict[str, np.ndarray] = {}
    dz = (dfeature - k["feature"] * (dfeature * k["feature"]).sum(axis=1, keepdims=True)) / k["len"]
    g["proj"] = k["pool"].T @ dz
    dx, g["gf"], g["bf"] = _norm_back(np.broadcast_to((dz @ w["proj"].T)[:, None, :] / TOKENS, k["nf"][0].shape), w["gf"], k["nf"])
    for i in range(depth(w) - 1, k["first"] - 1, -1):
        dx = _block_back(w, i, k["blocks"][i - k["first"]], dx, g)
    if "in" in k:
        g["pos"] = dx.sum(axis=0)
        dp = dx * k["live"]
        g["we"], g["be"] = _flat(k["in"], dp), dp.sum(axis=(0, 1))
    return g


def text_features(texts: list[str], seed: int = 42) -> np.ndarray:
    """Unit vectors of hashed lower-case words (damped counts), projected."""
    bins = np.zeros((len(texts), TEXT_BINS), np.float32)
    for i, t in enumerate(texts):
        for word in t.lower().split():
            bins[i, xxhash.xxh32_intdigest(word.strip(".,;:!?")) % TEXT_BINS] += 1
    turn = np.random.default_rng(seed).standard_normal((TEXT_BINS, OUT)).astype(np.float32) / np.sqrt(OUT)
    out = np.log1p(bins) @ turn
    return out / (np.linalg.norm(out, axis=1, keepdims=True) + 1e-8)


@dataclass
class Model:
    """A strategy's weights: the encoder, the class texts, and what the strategy adds."""

    strategy: str
    encoder: dict[str, np.ndarray]
    texts: np.ndarray
    extra: dict[str, np.ndarray] = field(default_factory=dict)
    rank: int = 8
    alpha: float = 16.0
    shape: str = "per_class"

    @classmethod
    def start(
        cls, strategy: str, encoder: dict, texts: np.ndarray, targets: tuple[str, ...] = ("attention", "perceptron"), rank: int = 8, alpha: float = 16.0, seed: int = 42, shape: str = "per_class", head: str = "text", head_start: str = "texts"
    ) -> Model:
        """`shape`: what a text-score probe scales and shifts, the scores of each class, all scores alike (scalar), or the text
        features' dimensions. `head`: whether low-rank adapters keep the class texts or train a linear head as well.
        `head_start`: a linear head starts from the class texts, zero, or seeded normal numbers."""
        classes, rng = len(texts), np.random.default_rng(seed)
        extra: dict[str, np.ndarray] = {}
        if strategy == "text_score":
            size = {"per_class": classes, "scalar": 1, "per_dim": OUT}[shape]
            extra = {"scale": np.ones(size, np.float32), "shift": np.zeros(size, np.float32)}
        if strategy in ("linear", "last_block", "full") or strategy == "low_rank" and head == "linear":
            weights = {"texts": HEAT * texts.T, "zero": np.zeros((OUT, classes)), "normal": np.random.default_rng([seed, 1]).standard_normal((OUT, classes)) * OUT**-0.5}[head_start]
            extra = {"head": weights.astype(np.float32), "bias": np.zeros(classes, np.float32)}
        if strategy == "low_rank":
            for name in (f"{i}.{n}" for i in range(depth(encoder)) for t in targets for n in ADAPTED[t]):
                a, b = encoder[name].shape
                extra |= {f"{name}.a": (rng.standard_normal((a, rank)) * a**-0.5).astype(np.float32), f"{name}.b": np.zeros((rank, b), np.float32)}
        return cls(strategy, encoder, texts, extra, rank, alpha, shape)

    def trainable(self) -> list[str]:
        """Names of the tensors that the strategy changes."""
        blocks = depth(self.encoder)
        own = {"last_block": block_names(blocks - 1) + FINAL, "full": EMBED + tuple(n for i in range(blocks) for n in block_names(i)) + FINAL + ("proj",)}.get(self.strategy, ())
        return [*own, *self.extra]

    def trainable_parameters(self) -> int:
        return sum(self.tensor(n).size for n in self.trainable())

    def adapters(self) -> list[str]:
        return [n[:-2] for n in self.extra if n.endswith(".a")]

    def merged(self, masks: dict[str, np.ndarray] | None = None) -> dict[str, np.ndarray]:
        """The encoder with low-rank updates folded in; with masks (examples x inputs of the matrix) each example has matrices
        of its own, in which the update reads the inputs that its mask leaves. The strategy's other models are as they are."""
        out = dict(self.encoder)
        for n in self.adapters():
            update = self.alpha / self.rank * (self.extra[f"{n}.a"] @ self.extra[f"{n}.b"])
            out[n] = out[n] + (masks[n][:, :, None] * update if masks else update)
        return out

    def scores(self, feature: np.ndarray) -> np.ndarray:
        if "head" in self.extra:
            return feature @ self.extra["head"] + self.extra["bias"]
        if self.strategy != "text_score":
            return HEAT * feature @ self.texts.T
        if self.shape == "per_dim":
            return HEAT * feature @ (self.texts * self.extra["scale"] + self.extra["shift"]).T
        return HEAT * feature @ self.texts.T * self.extra["scale"] + self.extra["shift"]

    def prepared(self, rasters: np.ndarray) -> np.ndarray:
        """What training reads of images that no step changes: features (frozen encoder), what the last block reads, what the
        first block reads (adapters), or the images."""
        if self.strategy == "full":
            return rasters
        x = embedded(self.encoder, patches(rasters))
        if self.strategy == "low_rank":
            return x
        x, _ = through(self.encoder, x, 0, depth(self.encoder) - 1)
        return x if self.strategy == "last_block" else forward(self.encoder, None, x, depth(self.encoder) - 1)[0]

    def features(self, inputs: np.ndarray, masks: dict[str, np.ndarray] | None = None) -> tuple[np.ndarray, dict | None, dict]:
        """Features of prepared images, what the backward pass needs, and the weights that were used."""
        if self.strategy in FROZEN:
            return inputs, None, self.encoder
        if self.strategy == "full":
            return *forward(self.encoder, patches(inputs)), self.encoder
        if self.strategy == "last_block":
            return *forward(self.encoder, None, inputs, depth(self.encoder) - 1), self.encoder
        w = self.merged(masks)
        return *forward(w, None, inputs), w

    def predict(self, rasters: np.ndarray) -> np.ndarray:
        return self.predict_prepared(self.prepared(rasters))

    def predict_prepared(self, inputs: np.ndarray) -> np.ndarray:
        return self.scores(self.features(inputs)[0]).argmax(axis=1)

    def gradients(self, rasters: np.ndarray, y: np.ndarray, dropout: float = 0.0, rng=None) -> tuple[float, dict[str, np.ndarray]]:
        return self.gradients_prepared(self.prepared(rasters), y, dropout, rng)

    def gradients_prepared(self, inputs: np.ndarray, y: np.ndarray, dropout: float = 0.0, rng=None) -> tuple[float, dict[str, np.ndarray]]:
        """Mean cross-entropy of a batch and the gradients of the trainable tensors. Dropout is drawn for each example."""
        masks = None
        if dropout and self.strategy == "low_rank":
            masks = {n: ((rng.random((len(inputs), len(self.encoder[n]))) >= dropout) / (1 - dropout)).astype(np.float32) for n in self.adapters()}
        feature, kept, w = self.features(inputs, masks)
        scores = self.scores(feature)
        p = np.exp(scores - scores.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        loss = float(-np.log(p[np.arange(len(y)), y] + 1e-12).mean())
        d = p.copy()
        d[np.arange(len(y)), y] -= 1
        d /= len(y)
        g: dict[str, np.ndarray] = {}
        if "head" in self.extra:
            g["head"], g["bias"], dfeature = feature.T @ d, d.sum(axis=0), d @ self.extra["head"].T
        elif self.strategy == "text_score":
            dtexts = HEAT * d.T @ feature
            cosine = HEAT * feature @ self.texts.T
            g["scale"], g["shift"] = {"per_class": ((d * cosine).sum(axis=0), d.sum(axis=0)), "scalar": (np.array([(d * cosine).sum()]), np.array([d.sum()])), "per_dim": ((dtexts * self.texts).sum(axis=0), dtexts.sum(axis=0))}[self.shape]
        else:
            dfeature = HEAT * d @ self.texts
        if kept is not None:
            g |= backward(w, kept, dfeature)
        for n in self.adapters():
            inner = self.alpha / self.rank * (np.einsum("ea,eab->ab", masks[n], g[n]) if masks else g[n])
            g[f"{n}.a"], g[f"{n}.b"] = inner @ self.extra[f"{n}.b"].T, self.extra[f"{n}.a"].T @ inner
        return loss, {n: g[n] for n in self.trainable()}

    def tensor(self, name: str) -> np.ndarray:
        return self.extra[name] if name in self.extra else self.encoder[name]

    def replaced(self, tensors: dict[str, np.ndarray]) -> Model:
        """The model with other tensors; an encoder that none of them belongs to is shared."""
        encoder = {k: tensors.get(k, v) for k, v in self.encoder.items()} if not tensors.keys().isdisjoint(self.encoder) else self.encoder
        return replace(self, encoder=encoder, extra={k: tensors.get(k, v) for k, v in self.extra.items()})
