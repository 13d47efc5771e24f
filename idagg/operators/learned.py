"""A learned set encoder with a fixed carried state, as a baseline: slots attend to identities, partitions add up, a decoder reads a count.

This is an independent small re-implementation in numpy (a fixed random trunk, sigmoid slot attention, additive partition states, a trained
decoder); its errors are its own and no published figure. Carried state: SLOTS x WIDTH sums and SLOTS x HEADS normalisers in 4-byte floats,
2,048 bytes, the size of a default register state.
"""

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SLOTS, WIDTH, HEADS = 16, 28, 4
STATE = SLOTS * WIDTH + SLOTS * HEADS
STATE_BYTES = 4 * STATE


def trunk_features(identity: np.ndarray, dim: int = WIDTH, seed: int = 0) -> np.ndarray:
    """A fixed feature vector of each identity, from its hash; shared by whatever reads identities and never trained."""
    h = pd.util.hash_array(np.asarray(identity, dtype=object)) ^ np.uint64(seed * 0x9E3779B97F4A7C15 % (1 << 64))
    out = np.empty((len(h), dim), np.float64)
    with np.errstate(over="ignore"):
        for k in range(dim):
            x = (h + np.uint64(k + 1)) * np.uint64(0xD6E8FEB86659FD93)
            x ^= x >> np.uint64(32)
            x *= np.uint64(0xD6E8FEB86659FD93)
            x ^= x >> np.uint64(29)
            out[:, k] = x.astype(np.float64) / 2.0**63 - 1
    return out


def trunk_column(identity):
    """The trunk as a column expression."""

    @F.pandas_udf("array<double>")
    def features(x: pd.Series) -> pd.Series:
        return pd.Series(list(trunk_features(x.to_numpy())))

    return features(identity)


@dataclass
class SetEncoder:
    """Parameters: slot keys (HEADS x SLOTS x WIDTH), value map (WIDTH x WIDTH) and the decoder's two layers."""

    keys: np.ndarray
    values: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    mean: np.ndarray
    scale: np.ndarray
    seed: int = 0

    @classmethod
    def create(cls, seed: int = 0, hidden: int = 16) -> "SetEncoder":
        r = np.random.default_rng(seed)
        return cls(r.normal(0, 1.5, (HEADS, SLOTS, WIDTH)), r.normal(0, WIDTH**-0.5, (WIDTH, WIDTH)), r.normal(0, STATE**-0.5, (STATE, hidden)),
                   np.zeros(hidden), r.normal(0, hidden**-0.5, hidden), 0.0, np.zeros(STATE), np.ones(STATE), seed)

    def partial_state(self, identities: np.ndarray, times: np.ndarray | None = None) -> np.ndarray:
        """Additive over any split of the records, and so not blind to repeats; times says how many records each identity stands for."""
        x = trunk_features(identities, seed=self.seed)
        gate = 1 / (1 + np.exp(-np.einsum("nd,hsd->nhs", x, self.keys)))
        if times is not None:
            gate = gate * np.asarray(times, float)[:, None, None]
        sums = np.einsum("nhs,nd->sd", gate, np.tanh(x @ self.values)) / HEADS
        return np.concatenate([sums.ravel(), gate.sum(0).T.ravel()])

    @staticmethod
    def merge(states: list[np.ndarray]) -> np.ndarray:
        return np.sum(states, axis=0)

    def _inputs(self, states: np.ndarray) -> np.ndarray:
        total = states[:, SLOTS * WIDTH :].sum(1, keepdims=True) + 1e-9
        shaped = np.concatenate([states[:, : SLOTS * WIDTH] / total, np.log1p(states[:, SLOTS * WIDTH :])], 1)
        return (shaped - self.mean) / self.scale

    def decode(self, states: np.ndarray) -> np.ndarray:
        z = np.tanh(self._inputs(np.atleast_2d(states)) @ self.w1 + self.b1)
        return np.exp(np.clip(z @ self.w2 + self.b2, 0, 25))

    def fit(self, states: np.ndarray, counts: np.ndarray, steps: int = 4_000, rate: float = 3e-3, decay: float = 1e-2) -> "SetEncoder":
        """Train the decoder on log counts by AdamW; slots and trunk stay as drawn."""
        self.mean, self.scale = np.zeros(STATE), np.ones(STATE)
        x = self._inputs(states)
        self.mean, self.scale = x.mean(0), x.std(0) + 1e-6
        x, y = (x - self.mean) / self.scale, np.log(np.maximum(1, counts))
        self.b2 = float(y.mean())
        p = [self.w1, self.b1, self.w2, np.array([self.b2])]
        m, s = [np.zeros_like(a) for a in p], [np.zeros_like(a) for a in p]
        for t in range(1, steps + 1):
            z = np.tanh(x @ p[0] + p[1])
            e = (z @ p[2] + p[3] - y) / len(y)
            gz = np.outer(e, p[2]) * (1 - z * z)
            for k, g in enumerate((x.T @ gz, gz.sum(0), z.T @ e, np.array([e.sum()]))):
                m[k] = 0.9 * m[k] + 0.1 * g
                s[k] = 0.999 * s[k] + 0.001 * g * g
                p[k] = p[k] * (1 - rate * decay * (k in (0, 2))) - rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(s[k] / (1 - 0.999**t)) + 1e-8)
        self.w1, self.b1, self.w2, self.b2 = p[0], p[1], p[2], float(p[3][0])
        return self


class SumPoolEncoder(SetEncoder):
    """Sum pooling without attention: every slot counts every record alike."""

    def partial_state(self, identities: np.ndarray, times: np.ndarray | None = None) -> np.ndarray:
        x = np.tanh(trunk_features(identities, seed=self.seed) @ self.values)
        times = np.ones(len(x)) if times is None else np.asarray(times, float)
        return np.concatenate([np.tile(times @ x, SLOTS), np.full(SLOTS * HEADS, times.sum())])


def encode_states(records: DataFrame, key: str, encoder: SetEncoder, identity: str = "identity", times: str | None = None) -> DataFrame:
    """(key, state array<double>): partial sums in each task, then added up by key. A row stands for as many records as column times says."""
    shared = records.sparkSession.sparkContext.broadcast(encoder)  # 70 KB of parameters
    kind = records.schema[key].dataType.simpleString()

    def partial(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            rows = [(k, shared.value.partial_state(g[identity].to_numpy(), g[times].to_numpy() if times else None).tolist()) for k, g in f.groupby(key, sort=False)]
            yield pd.DataFrame(rows, columns=[key, "state"])

    parts = records.select(key, identity, *([times] if times else [])).where(F.col(identity).isNotNull()).mapInPandas(partial, f"{key} {kind}, state array<double>")
    summed = parts.select(key, F.posexplode("state").alias("__k", "x")).groupBy(key, "__k").agg(F.sum("x").alias("x"))
    return summed.groupBy(key).agg(F.transform(F.array_sort(F.collect_list(F.struct("__k", "x"))), lambda s: s["x"]).alias("state"))


def decode_states(states: DataFrame, key: str, encoder: SetEncoder) -> DataFrame:
    shared = states.sparkSession.sparkContext.broadcast(encoder)

    @F.pandas_udf("double")
    def count(s: pd.Series) -> pd.Series:
        return pd.Series(shared.value.decode(np.array(s.tolist()))) if len(s) else pd.Series([], dtype=float)

    return states.select(key, count("state").alias("estimate"))
