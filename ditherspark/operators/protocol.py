"""One round of compressed descent: what a worker sends, what the server makes of it, for every method and baseline.

The same functions run in executors (workers pack, those that decode unpack and sum) and on the driver (the server's
message), and in the seed-parallel runner, which skips the bytes of the workers' messages, so both runners give the same
messages for the same key. Uncompressed numbers go as floats of 32 bits.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np

from ditherspark.functions.closed_forms import amplitudes, next_pow2, wire_bits
from ditherspark.functions.rng import STREAMS, counter_hash
from ditherspark.operators.codec import decode_rows, encode_rows, sign_keys, signs_of
from ditherspark.operators.quantize import level_bits, pack_levels, pack_numbers, unpack_levels, unpack_numbers


@dataclass(frozen=True)
class RunConfig:
    """A run. ``up`` is none, codec, sign, random_k or ternary; ``down`` is none, codec or sign. ``schedule`` is constant,
    inv_sqrt (1/sqrt(rounds)) or a list of steps. ``server_amp`` is rule or observed (the round's largest flattened entry,
    64 more bits). ``eps_scope`` is worker or round (one sign string, so the server sums levels and inverts once)."""

    d: int
    n_workers: int = 16
    m_prime: int = 1
    k: int = 255
    alpha: float = 2.0
    alpha_s: float = 2.0
    bound: float = 1.0
    delta: float = 0.1
    rounds: int = 100
    up: str = "codec"
    down: str = "codec"
    basis: str = "butterfly"
    dither: bool = True
    server_amp: str = "rule"
    eps_scope: str = "worker"
    eps_wire: str = "bits"
    schedule: str | tuple[float, ...] = "constant"
    keep: int = 4
    radius: float = 0.0
    clip_norm: float = 0.0
    loss: str = "lsq"

    @property
    def width(self) -> int:
        """The dimension on the wire."""
        return next_pow2(self.d) if "codec" in (self.up, self.down) else self.d

    def step(self, t: int) -> float:
        if isinstance(self.schedule, tuple):
            return self.schedule[t]
        return self.rounds**-0.5 if self.schedule == "inv_sqrt" else self.delta

    def amplitudes(self) -> tuple[float, float]:
        return amplitudes(self.alpha, self.alpha_s, self.bound, self.width)


def method(name: str, base: RunConfig) -> RunConfig:
    """``base`` as the named method."""
    plain = {"up": "none", "down": "none"}
    changes = {
        "plain": plain,
        "local": plain | {"n_workers": 1},
        "onebit": {},
        "up_only": {"down": "none"},
        "down_only": {"up": "none"},
        "vote": {"up": "sign", "down": "sign"},
        "sign_mean": {"up": "sign", "down": "none"},
        "no_flatten": {"basis": "identity"},
        "no_dither": {"dither": False},
        "shared_sign": {"eps_scope": "round"},
        "observed": {"server_amp": "observed"},
        "fourier": {"basis": "fourier"},
        "cosine": {"basis": "cosine"},
        "random_k": {"up": "random_k", "down": "none"},
        "ternary": {"up": "ternary", "down": "none"},
    }
    return replace(base, **changes[name])


def one(x: np.ndarray) -> np.ndarray:
    """Sign with sgn(0) = +1."""
    return np.where(x >= 0, 1.0, -1.0)


def pad(g: np.ndarray, width: int) -> np.ndarray:
    if g.shape[1] == width:
        return g
    return np.concatenate([g, np.zeros((len(g), width - g.shape[1]))], axis=1)


@dataclass
class Up:
    """What a batch of workers sends: whole-number levels (rows, entries), floats of 32 bits (rows, some), and the keys of
    the sign strings. Any part may be absent, as the method has it."""

    levels: np.ndarray | None = None
    floats: np.ndarray | None = None
    keys: np.ndarray | None = None
    clipped: np.ndarray | None = None


def encode_up(g: np.ndarray, workers: np.ndarray, cfg: RunConfig, t: int, seed: int) -> Up:
    """Messages for gradients ``g``, a row a worker."""
    if cfg.clip_norm:
        norm = np.linalg.norm(g, axis=1, keepdims=True)
        g = g * np.minimum(1, cfg.clip_norm / np.maximum(norm, 1e-300))
    calm, at = np.zeros(len(g), bool), np.asarray(workers, np.int64)[:, None]
    if cfg.up == "none":
        return Up(floats=g.astype(np.float32), clipped=calm)
    if cfg.up == "sign":
        return Up(levels=one(g).astype(np.int64), clipped=calm)
    if cfg.up == "random_k":  # kept coordinates, scaled up: unbiased, with a variance that grows with d/keep
        d, keep = g.shape[1], min(cfg.keep, g.shape[1])
        order = np.argsort(counter_hash(seed, STREAMS["keep"], t, at, np.arange(d)), axis=1, kind="stable")[:, :keep]
        return Up(levels=order, floats=(np.take_along_axis(g, order, 1) * d / keep).astype(np.float32), clipped=calm)
    if cfg.up == "ternary":  # sign times the norm, kept with probability |g_i| / norm
        norm = np.linalg.norm(g, axis=1, keepdims=True)
        u = (2.0 * counter_hash(seed, STREAMS["ternary"], t, at, np.arange(g.shape[1])) + 1) / 8589934592.0
        return Up(levels=np.where(u * norm < np.abs(g), np.sign(g), 0).astype(np.int64), floats=norm.astype(np.float32), clipped=calm)
    lam, _ = cfg.amplitudes()
    q, _, z = encode_rows(pad(g, cfg.width), workers, lam, 1, seed, t, "worker", cfg.basis, cfg.eps_scope, cfg.dither)
    keys = None if cfg.basis == "identity" else sign_keys(seed, "worker", t, workers, cfg.eps_scope)
    return Up(levels=q, keys=keys, clipped=np.abs(z).max(axis=1) > lam)


def decode_up(up: Up, cfg: RunConfig, eps: np.ndarray | None = None) -> np.ndarray:
    """Rows whose sum is that of the workers' decoded vectors. Sign strings come from ``eps`` or the messages' keys; with
    one string for all, levels are summed first and inverted once, as decoding is linear."""
    if cfg.up == "none":
        return pad(up.floats.astype(np.float64), cfg.width)
    if cfg.up == "sign":
        return up.levels.astype(np.float64)
    if cfg.up == "random_k":
        out = np.zeros((len(up.levels), cfg.d))
        np.put_along_axis(out, up.levels, up.floats.astype(np.float64), 1)
        return out
    if cfg.up == "ternary":
        return up.levels * up.floats.astype(np.float64)
    lam, _ = cfg.amplitudes()
    if eps is None:
        eps = np.ones((len(up.levels), cfg.width), np.int64) if cfg.basis == "identity" else signs_of(up.keys, cfg.width)
    if cfg.eps_scope == "round" and len(up.levels):
        return decode_rows(up.levels.sum(axis=0, keepdims=True), eps[:1], lam, 1, cfg.basis)
    return decode_rows(up.levels, eps, lam, 1, cfg.basis)


def entries(cfg: RunConfig) -> int:
    """Levels of a codec message."""
    return 2 * cfg.width if cfg.basis == "fourier" else cfg.width


def pack_up(up: Up, cfg: RunConfig) -> tuple[np.ndarray, np.ndarray]:
    """(message bytes, sign bytes) of each worker, as rows: levels in the fewest whole bits, floats in 32, and the sign
    string in d bits or, with ``eps_wire`` seed, as the 8 bytes it follows from."""
    n = len(up.clipped)
    parts, eps = [], np.zeros((n, 0), np.uint8)
    if up.floats is not None:
        parts.append(np.ascontiguousarray(up.floats, "<f4").view(np.uint8).reshape(n, -1))
    if cfg.up == "random_k":
        parts.append(pack_numbers(up.levels, max(1, (cfg.d - 1).bit_length())))
    elif cfg.up == "ternary":
        parts.append(pack_numbers(up.levels + 1, 2))
    elif up.levels is not None:
        parts.append(pack_numbers((up.levels + 1) >> 1, 1))
    if up.keys is not None and cfg.eps_wire == "seed":
        eps = np.ascontiguousarray(up.keys, "<u4").view(np.uint8).reshape(n, 8)
    elif up.keys is not None and cfg.eps_wire == "bits":
        eps = np.packbits(signs_of(up.keys, cfg.width) > 0, axis=1, bitorder="little")
    return np.concatenate(parts, axis=1), eps


def unpack_up(packed: np.ndarray, eps: np.ndarray, cfg: RunConfig) -> np.ndarray:
    """``decode_up`` of what arrived: nothing is used but the bytes."""
    n, up, signs = len(packed), Up(), None
    floats = {"none": cfg.d, "random_k": min(cfg.keep, cfg.d), "ternary": 1}.get(cfg.up, 0)
    if floats:
        up.floats = np.ascontiguousarray(packed[:, : 4 * floats]).view("<f4").reshape(n, floats)
    rest = packed[:, 4 * floats :]
    if cfg.up == "random_k":
        up.levels = unpack_numbers(rest, max(1, (cfg.d - 1).bit_length()), floats)
    elif cfg.up == "ternary":
        up.levels = unpack_numbers(rest, 2, cfg.d) - 1
    elif cfg.up != "none":
        up.levels = 2 * unpack_numbers(rest, 1, cfg.d if cfg.up == "sign" else entries(cfg)) - 1
    if cfg.up == "codec" and cfg.basis != "identity":
        if cfg.eps_wire == "seed":
            up.keys = np.ascontiguousarray(eps).view("<u4").reshape(n, 2)
        else:
            signs = 2 * np.unpackbits(eps, axis=1, bitorder="little")[:, : cfg.width].astype(np.int64) - 1
    return decode_up(up, cfg, signs)


def send_up(g: np.ndarray, workers: np.ndarray, cfg: RunConfig, t: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """(what the server decodes from the workers, whether a worker clipped): the same as through bytes."""
    up = encode_up(g, workers, cfg, t, seed)
    return decode_up(up, cfg), up.clipped


def pack_down(w: np.ndarray, cfg: RunConfig, t: int, seed: int) -> tuple[bytes, bool]:
    """(the server's message, whether it clipped): floats of 32 bits, signs, or the observed amplitude's 8 bytes if any,
    levels, and the sign string or its seed."""
    if cfg.down == "none":
        return w[: cfg.d].astype("<f4").tobytes(), False
    if cfg.down == "sign":
        return pack_levels(one(w)[None], 1)[0], False
    _, lam = cfg.amplitudes()
    at, head = np.zeros(1, np.int64), b""
    if cfg.server_amp == "observed":
        _, _, z = encode_rows(w[None], at, 1.0, 1, seed, t, "server", cfg.basis, "worker", False)
        lam = float(np.abs(z).max()) or 1.0
        head = np.float64(lam).tobytes()
    q, eps, z = encode_rows(w[None], at, lam, cfg.k, seed, t, "server", cfg.basis, "worker", cfg.dither)
    tail = b""
    if cfg.basis != "identity":
        tail = sign_keys(seed, "server", t, at).astype("<u4").tobytes() if cfg.eps_wire == "seed" else np.packbits(eps[0] > 0, bitorder="little").tobytes()
    return head + pack_levels(q, cfg.k)[0] + tail, bool(np.abs(z).max() > lam * (1 + 1e-12))


def unpack_down(message: bytes, cfg: RunConfig) -> np.ndarray:
    """The direction that every worker decodes."""
    if cfg.down == "none":
        return np.frombuffer(message, "<f4").astype(np.float64)
    if cfg.down == "sign":
        return unpack_levels([message], 1, cfg.width)[0].astype(np.float64)
    _, lam = cfg.amplitudes()
    if cfg.server_amp == "observed":
        lam, message = float(np.frombuffer(message[:8], "<f8")[0]), message[8:]
    size = -(-entries(cfg) * level_bits(cfg.k) // 8)
    q, tail = unpack_levels([message[:size]], cfg.k, entries(cfg)), message[size:]
    if cfg.basis == "identity":
        eps = np.ones((1, cfg.width), np.int64)
    elif cfg.eps_wire == "seed":
        eps = signs_of(np.frombuffer(tail, "<u4")[None], cfg.width)
    else:
        eps = 2 * np.unpackbits(np.frombuffer(tail, np.uint8)[None], axis=1, bitorder="little")[:, : cfg.width].astype(np.int64) - 1
    return decode_rows(q, eps, lam, cfg.k, cfg.basis)[0]


def send_down(w: np.ndarray, cfg: RunConfig, t: int, seed: int) -> tuple[np.ndarray, bool]:
    """(the direction that all workers decode from the server's mean ``w``, whether the server clipped)."""
    message, clip = pack_down(w, cfg, t, seed)
    return unpack_down(message, cfg), clip


def traffic(cfg: RunConfig) -> tuple[float, float]:
    """(bits up of all workers, bits down) of a round, as counts of information."""
    n, d, w = cfg.n_workers, cfg.d, cfg.width
    size = {"butterfly": w, "cosine": w, "identity": w, "fourier": 2 * w}[cfg.basis]
    codec = wire_bits(w, n, cfg.k, "none" if cfg.basis == "identity" else cfg.eps_wire)
    up = {"none": 32 * d * n, "sign": d * n, "random_k": n * cfg.keep * (32 + np.log2(d)), "ternary": n * (d * np.log2(3) + 32), "codec": codec["up_all"] + n * (size - w)}[cfg.up]
    down = {"none": 32 * d, "sign": d, "codec": codec["down"] + (size - w) * np.log2(cfg.k + 1) + 64 * (cfg.server_amp == "observed")}[cfg.down]
    return float(up), float(down)


# Losses: value and gradient factor at margins z = <a, x>; the gradient of a row is factor * a.
def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -700, 700)))


def loss_value(kind: str, z: np.ndarray, y: np.ndarray) -> np.ndarray:
    if kind == "logistic":
        return np.logaddexp(0, -y * z)
    return (_sigmoid(z) - (y + 1) / 2) ** 2 if kind == "sigmoid" else (z - y) ** 2


def loss_factor(kind: str, z: np.ndarray, y: np.ndarray) -> np.ndarray:
    """``lsq`` squared error, ``logistic`` with labels -1/+1 (unit rows: gradients up to 1), ``sigmoid`` squared error of a
    sigmoid (not convex; unit rows: gradients up to 1/2)."""
    if kind == "logistic":
        return -y * _sigmoid(-y * z)
    if kind == "sigmoid":
        s = _sigmoid(z)
        return 2 * (s - (y + 1) / 2) * s * (1 - s)
    return 2 * (z - y)
