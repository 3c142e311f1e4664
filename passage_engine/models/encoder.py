"""Transformer encoder over blocks of sentences, and the taggers built on it.

Parameters are a flat dictionary of arrays, so they ship as one compressed blob and gradients add up
by name. Token ids come from hashing words into a vocabulary (``hash_ids``) or from sub-word pieces.
"""

from __future__ import annotations

import io
import zlib
from dataclasses import asdict, dataclass, field

import numpy as np

from ..functions.tokens import END, spelled
from .autograd import Var, concat, cross_entropy, gelu, norm, sigmoid, softmax, stack, tanh

MARKER, SEPARATOR, MASK, SPECIALS = 0, 1, 2, 4


@dataclass(frozen=True)
class Config:
    """Sizes and switches. ``kind``: block, local, two_level, recurrent."""

    kind: str = "block"
    vocab: int = 2048
    phones: int = 0  # symbols of the phone table; 0: no phones
    phone_pool: str = "mean"  # or "sum"
    phone_spread: str = "all"  # pieces of a word that get its phones, or "first"
    width: int = 32
    heads: int = 2
    layers: int = 2
    max_tokens: int = 512
    max_sents: int = 60
    context: int = 128  # of the local-context classifier, on each side
    segments: int = 2
    joint: bool = False  # two_level: the upper stack reads the vectors of a first stack that saw all sentences of the block
    classes: int = 2
    seed: int = 11
    labels: tuple = field(default=("inside", "boundary"))


#: The published sizes, for counting parameters and for weights from elsewhere.
BASE = Config(vocab=30522, width=768, heads=12, layers=12)
LARGE = Config(vocab=30522, width=1024, heads=16, layers=24)


def shapes(cfg: Config) -> dict[str, tuple]:
    w, out = cfg.width, {}
    out["tok"], out["pos"], out["seg"] = (cfg.vocab, w), (cfg.max_tokens, w), (cfg.segments, w)
    out["in.g"], out["in.b"] = (w,), (w,)
    if cfg.phones:
        out["phone"] = (cfg.phones, w)
    stacks = [("enc", cfg.layers)] + ([("doc", cfg.layers)] if cfg.kind == "two_level" else [])
    for name, n in stacks:
        for i in range(n):
            p = f"{name}{i}."
            out |= {p + "q": (w, w), p + "k": (w, w), p + "v": (w, w), p + "o": (w, w), p + "qb": (w,), p + "kb": (w,), p + "vb": (w,), p + "ob": (w,), p + "g1": (w,), p + "b1": (w,), p + "f1": (w, 4 * w), p + "fb1": (4 * w,), p + "f2": (4 * w, w), p + "fb2": (w,), p + "g2": (w,), p + "b2": (w,)}
    if cfg.kind == "two_level":
        out["spos"] = (cfg.max_sents + 1, w)
    if cfg.kind == "recurrent":
        for d in ("fw.", "bw."):
            out |= {d + "x": (w, 4 * w), d + "h": (w, 4 * w), d + "b": (4 * w,)}
    out["head.w"], out["head.b"] = ((2 if cfg.kind == "recurrent" else 1) * w, cfg.classes), (cfg.classes,)
    return out


def n_params(cfg: Config) -> int:
    return sum(int(np.prod(s)) for s in shapes(cfg).values())


def init(cfg: Config) -> dict[str, np.ndarray]:
    rng, out = np.random.default_rng(cfg.seed), {}
    for name, s in shapes(cfg).items():
        last = name.rsplit(".", 1)[-1]
        if last in ("g", "g1", "g2"):
            out[name] = np.ones(s)
        elif len(s) == 1:
            out[name] = np.zeros(s)
        else:
            out[name] = rng.standard_normal(s) * (0.02 if s[0] > 4 * cfg.width else 1 / np.sqrt(s[0]))
    for name in ("tok", "pos", "seg", "phone", "spos"):
        if name in out:
            out[name] = rng.standard_normal(out[name].shape) * 0.1
    return out


def save(cfg: Config, params: dict[str, np.ndarray]) -> bytes:
    buf = io.BytesIO()
    np.savez_compressed(buf, __cfg=np.array(repr(asdict(cfg))), **params)
    return buf.getvalue()


def load(blob: bytes) -> tuple[Config, dict[str, np.ndarray]]:
    import ast

    with np.load(io.BytesIO(blob), allow_pickle=False) as z:
        return Config(**ast.literal_eval(str(z["__cfg"]))), {k: z[k] for k in z.files if k != "__cfg"}


def hash_ids(words: list[str], vocab: int) -> list[int]:
    """Stable word ids without a vocabulary table."""
    return [SPECIALS + zlib.crc32(w.lower().encode()) % (vocab - SPECIALS) for w in words]


def phone_ids(words: list[str], table: dict[str, list[str]], size: int, spread: str = "all") -> list[list[int]]:
    """Symbols of each word's first pronunciation; none for unknown words.

    Of sub-words, all pieces of a word get the word's symbols (``spread`` 'all') or its first piece alone.
    """
    of = lambda w: [1 + zlib.crc32(p.encode()) % (size - 1) for p in table.get(w.lower(), [])]
    if not any(w.endswith(END) for w in words):
        return [of(w) for w in words]
    out, held = [], []
    for w in words:
        held.append(w)
        if w.endswith(END):
            got = of(spelled("".join(held).removesuffix(END)))
            out += [got if spread == "all" or i == 0 else [] for i in range(len(held))]
            held = []
    return out + [[] for _ in held]


#: Places of a slice that inference encodes at once: what a layer makes of them stays in a core's cache.
SLICE = 512


def plain_norm(x: np.ndarray, gain: np.ndarray, bias: np.ndarray, eps: float = 1e-6) -> np.ndarray:
    """``norm`` without a way back; overwrites x."""
    x -= x.mean(axis=-1, keepdims=True)
    x *= 1 / np.sqrt(np.einsum("...i,...i->...", x, x)[..., None] / x.shape[-1] + eps)
    x *= gain
    x += bias
    return x


def plain_gelu(x: np.ndarray) -> np.ndarray:
    """``gelu`` without a way back; overwrites x."""
    y = x * x
    y *= 0.044715
    y += 1
    y *= x
    y *= np.sqrt(2 / np.pi)
    np.tanh(y, out=y)
    y += 1
    y *= x
    y *= 0.5
    return y


@dataclass
class Block:
    """A run of sentences: token ids of each, optionally phone ids of each token, labels."""

    sents: list[list[int]]
    phones: list[list[list[int]]] | None = None
    labels: list[int] | None = None


class Network:
    """Forward passes of one configuration over a batch of blocks."""

    def __init__(self, cfg: Config, params: dict[str, np.ndarray], train: bool = False, dropout: float = 0.0, seed: int = 0):
        self.cfg, self.p = cfg, {k: Var(v, needs=train) for k, v in params.items()}
        self.drop, self.rng, self.train = dropout if train else 0.0, np.random.default_rng(seed), train

    def dropped(self, x: Var) -> Var:
        if not self.drop:
            return x
        return x * ((self.rng.random(x.value.shape) >= self.drop) / (1 - self.drop))

    def embed(self, ids: np.ndarray, seg: np.ndarray, phones: list | None) -> Var:
        """Token + position + segment vectors, plus the mean (or sum) of each token's phone vectors."""
        p = self.p
        x = p["tok"][ids] + p["pos"][np.arange(ids.shape[1])] + p["seg"][seg]
        if self.cfg.phones and phones is not None:
            most = max((len(t) for row in phones for t in row), default=0)
            if most:
                at = np.zeros((*ids.shape, most), np.int64)
                weight = np.zeros((*ids.shape, most, 1))
                for i, row in enumerate(phones):
                    for j, t in enumerate(row):
                        at[i, j, : len(t)] = t
                        weight[i, j, : len(t)] = (1 / len(t) if self.cfg.phone_pool == "mean" else 1) if t else 0
                v = p["phone"][at] * weight
                total = v[:, :, 0]
                for k in range(1, most):
                    total = total + v[:, :, k]
                x = x + total
        return self.dropped(norm(x, p["in.g"], p["in.b"]))

    def stack(self, x: Var, mask: np.ndarray, name: str = "enc") -> Var:
        """Post-norm transformer layers; mask is true at real places."""
        c, p = self.cfg, self.p
        b, t, w = x.value.shape
        d = w // c.heads
        away = np.where(mask, 0.0, -1e9)[:, None, None, :]
        for i in range(c.layers):
            n = f"{name}{i}."
            heads = lambda k: (x @ p[n + k] + p[n + k + "b"]).reshape(b, t, c.heads, d).transpose(0, 2, 1, 3)  # noqa: E731, B023
            q, k, v = heads("q"), heads("k"), heads("v")
            a = softmax((q @ k.transpose(0, 1, 3, 2)) * (1 / np.sqrt(d)) + away)
            y = (self.dropped(a) @ v).transpose(0, 2, 1, 3).reshape(b, t, w) @ p[n + "o"] + p[n + "ob"]
            x = norm(x + self.dropped(y), p[n + "g1"], p[n + "b1"])
            y = gelu(x @ p[n + "f1"] + p[n + "fb1"]) @ p[n + "f2"] + p[n + "fb2"]
            x = norm(x + self.dropped(y), p[n + "g2"], p[n + "b2"])
        return x

    def plain_stack(self, x: np.ndarray, mask: np.ndarray, name: str = "enc", lead: bool = False) -> np.ndarray:
        """``stack`` without a way back; overwrites x. lead: only the leading place's state is asked for.

        The last layer then makes that state alone.
        """
        c, p = self.cfg, {k: v.value for k, v in self.p.items()}
        b, t, w = x.shape
        d = w // c.heads
        away = np.where(mask, 0.0, -1e9)[:, None, None, :]
        for i in range(c.layers):
            n = f"{name}{i}."
            asked = x[:, :1] if lead and i == c.layers - 1 else x
            heads = lambda y, k: (y @ p[n + k] + p[n + k + "b"]).reshape(b, y.shape[1], c.heads, d).transpose(0, 2, 1, 3)  # noqa: E731, B023
            a = (heads(asked, "q") * (1 / np.sqrt(d))) @ heads(x, "k").transpose(0, 1, 3, 2)
            a += away
            a -= a.max(axis=-1, keepdims=True)
            np.exp(a, out=a)
            a /= a.sum(axis=-1, keepdims=True)
            y = (a @ heads(x, "v")).transpose(0, 2, 1, 3).reshape(b, asked.shape[1], w) @ p[n + "o"]
            y += p[n + "ob"]
            y += asked
            x = plain_norm(y, p[n + "g1"], p[n + "b1"])
            y = x @ p[n + "f1"]
            y += p[n + "fb1"]
            y = plain_gelu(y) @ p[n + "f2"]
            y += p[n + "fb2"]
            y += x
            x = plain_norm(y, p[n + "g2"], p[n + "b2"])
        return x

    def encoded(self, ids: np.ndarray, seg: np.ndarray, mask: np.ndarray, phones: list | None = None, lead: bool = False) -> Var:
        """States of all places, or of the leading ones alone (lead).

        In training one differentiable pass. Else slices of a few rows, each cut to its own longest row,
        so that neither padding nor arrays beyond the cache cost time.
        """
        if self.train:
            h = self.stack(self.embed(ids, seg, phones), mask)
            return h[:, 0] if lead else h
        p = {k: self.p[k].value for k in ("tok", "pos", "seg", "in.g", "in.b")}
        size = mask.sum(axis=1)
        out = np.zeros((len(ids), self.cfg.width) if lead else (*ids.shape, self.cfg.width))
        order, i = np.argsort(-size, kind="stable"), 0  # the first row of a slice is its longest
        while i < len(order):
            rows = order[i : i + max(1, SLICE // int(size[order[i]]))]
            t = int(size[rows[0]])
            if self.cfg.phones and phones is not None:
                x = self.embed(ids[rows, :t], seg[rows, :t], [phones[r] for r in rows]).value
            else:
                x = p["tok"][ids[rows, :t]]
                x += p["pos"][:t]
                x += p["seg"][seg[rows, :t]]
                x = plain_norm(x, p["in.g"], p["in.b"])
            h = self.plain_stack(x, mask[rows, :t], lead=lead)
            if lead:
                out[rows] = h[:, 0]
            else:
                out[rows, :t] = h
            i += len(rows)
        return Var(out)

    def sentence_vectors(self, blocks: list[Block]) -> tuple[Var, np.ndarray, int]:
        """One pass over marker + all tokens; mean of each sentence's final states. Also (real, padded) tokens."""
        c = self.cfg
        rows = []
        for blk in blocks:
            ids, owner, ph = [MARKER], [-1], [[]]
            for m, s in enumerate(blk.sents):
                room = c.max_tokens - len(ids)
                s = s[:room] if room > 0 else []
                ids += s
                owner += [m] * len(s)
                ph += (blk.phones[m][: len(s)] if blk.phones else [[]] * len(s))
            rows.append((ids, owner, ph))
        t = max(len(r[0]) for r in rows)
        n = max(len(blk.sents) for blk in blocks)
        ids = np.zeros((len(rows), t), np.int64)
        mask = np.zeros((len(rows), t), bool)
        pool = np.zeros((len(rows), n, t))
        phones = [r[2] for r in rows]
        for i, (tok, owner, _) in enumerate(rows):
            ids[i, : len(tok)], mask[i, : len(tok)] = tok, True
            of = np.array(owner)
            places = np.flatnonzero(of >= 0)
            pool[i, of[places], places] = 1
        pool /= np.maximum(pool.sum(axis=2, keepdims=True), 1)
        h = self.encoded(ids, np.zeros_like(ids), mask, phones)
        real = np.zeros((len(rows), n), bool)
        for i, blk in enumerate(blocks):
            real[i, : len(blk.sents)] = True
        return Var(pool) @ h, real, int(mask.sum())

    def recurrent(self, s: Var, real: np.ndarray) -> Var:
        """Bidirectional long short-term memory over sentence vectors."""
        b, n, w = s.value.shape
        outs = []
        for d in ("fw.", "bw."):
            order = range(n) if d == "fw." else range(n - 1, -1, -1)
            hid, cell, states = Var(np.zeros((b, w))), Var(np.zeros((b, w))), {}
            for t in order:
                z = s[:, t] @ self.p[d + "x"] + hid @ self.p[d + "h"] + self.p[d + "b"]
                i, f, o, g = sigmoid(z[:, :w]), sigmoid(z[:, w : 2 * w] + 1.0), sigmoid(z[:, 2 * w : 3 * w]), tanh(z[:, 3 * w :])
                keep = real[:, t : t + 1].astype(float)
                cell = (f * cell + i * g) * keep
                hid = (o * tanh(cell)) * keep
                states[t] = hid
            outs.append(stack([states[t] for t in range(n)], 1))
        return concat(outs)

    def two_level(self, blocks: list[Block]) -> tuple[Var, np.ndarray, int]:
        """Each sentence encoded alone (joint: all in one pass), then an encoder over the sentence vectors."""
        if self.cfg.joint:
            v, real, tokens = self.sentence_vectors(blocks)
            x = v + self.p["spos"][np.minimum(np.arange(v.value.shape[1]), self.cfg.max_sents)]
            return self.stack(x, real, "doc"), real, tokens
        flat = [Block([s], [blk.phones[m]] if blk.phones else None) for blk in blocks for m, s in enumerate(blk.sents)]
        v, _, tokens = self.sentence_vectors(flat)
        n = max(len(blk.sents) for blk in blocks)
        at = np.zeros((len(blocks), n), np.int64)
        real = np.zeros((len(blocks), n), bool)
        k = 0
        for i, blk in enumerate(blocks):
            at[i, : len(blk.sents)] = np.arange(k, k + len(blk.sents))
            real[i, : len(blk.sents)] = True
            k += len(blk.sents)
        x = v[:, 0][at] + self.p["spos"][np.minimum(np.arange(n), self.cfg.max_sents)]
        return self.stack(x, real, "doc"), real, tokens

    def local(self, blocks: list[Block]) -> tuple[Var, np.ndarray, int]:
        """One pass for each break: marker, left context, separator, right context; the marker's state."""
        c = self.cfg
        pairs, where = [], []
        for i, blk in enumerate(blocks):
            flat = [x for s in blk.sents for x in s]
            ends = np.cumsum([len(s) for s in blk.sents])
            for m, e in enumerate(ends):
                pairs.append((flat[max(0, e - c.context) : e], flat[e : e + c.context]))
                where.append((i, m))
        t = max(len(a) + len(b) + 2 for a, b in pairs)
        ids, seg, mask = (np.zeros((len(pairs), t), np.int64) for _ in range(3))
        for r, (a, b) in enumerate(pairs):
            row = [MARKER, *a, SEPARATOR, *b]
            ids[r, : len(row)], mask[r, : len(row)] = row, 1
            seg[r, len(a) + 1 : len(row)] = 1
        h = self.encoded(ids, seg, mask > 0, lead=True)
        n = max(len(blk.sents) for blk in blocks)
        at = np.zeros((len(blocks), n), np.int64)
        real = np.zeros((len(blocks), n), bool)
        for r, (i, m) in enumerate(where):
            at[i, m], real[i, m] = r, True
        return h[at], real, int(mask.sum())

    def logits(self, blocks: list[Block]) -> tuple[Var, np.ndarray, int]:
        kind = self.cfg.kind
        v, real, tokens = {"two_level": self.two_level, "local": self.local}.get(kind, self.sentence_vectors)(blocks)
        if kind == "recurrent":
            v = self.recurrent(v, real)
        return v @ self.p["head.w"] + self.p["head.b"], real, tokens

    def probabilities(self, blocks: list[Block]) -> tuple[list[np.ndarray], int]:
        z, real, tokens = self.logits(blocks)
        p = softmax(z).value[..., -1]
        return [row[ok] for row, ok in zip(p, real, strict=True)], tokens

    def loss(self, blocks: list[Block]) -> tuple[Var, int]:
        z, real, _ = self.logits(blocks)
        y = np.full(real.shape, -1, np.int64)
        for i, blk in enumerate(blocks):
            y[i, : len(blk.sents)] = blk.labels
        judged = real & (y >= 0)  # a label below 0 isn't judged
        return cross_entropy(z, np.maximum(y, 0), judged.astype(float)), int(judged.sum())


class Adam:
    """Standard Adam; the state lives on the driver."""

    def __init__(self, rate: float = 5e-5, b1: float = 0.9, b2: float = 0.999, eps: float = 1e-8):
        self.rate, self.b1, self.b2, self.eps, self.t, self.m, self.v = rate, b1, b2, eps, 0, {}, {}

    def step(self, params: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] = self.b1 * self.m.get(k, 0.0) + (1 - self.b1) * g
            self.v[k] = self.b2 * self.v.get(k, 0.0) + (1 - self.b2) * g * g
            params[k] = params[k] - self.rate * (self.m[k] / (1 - self.b1**self.t)) / (np.sqrt(self.v[k] / (1 - self.b2**self.t)) + self.eps)
