"""Counter-based uniforms: a draw follows from its key alone, so retries, resumes and partitioning never change history."""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np

_SCALE = float(1 << 52)


def uniform(seed: int, stream: str, k: int, t: int, coord: int = 0) -> float:
    """Uniform in [0, 1) from the first 13 hexadecimal digits of the key's md5."""
    return int(hashlib.md5(f"{seed}|{stream}|{k}|{t}|{coord}".encode()).hexdigest()[:13], 16) / _SCALE


@lru_cache(maxsize=16)
def _coords(d: int) -> list[bytes]:
    return [b"%d" % i for i in range(d)]


@lru_cache(maxsize=4096)
def uniforms(seed: int, stream: str, k: int, t: int, d: int) -> np.ndarray:
    """One draw per coordinate; the runs of a batch share them."""
    key, md5 = f"{seed}|{stream}|{k}|{t}|".encode(), hashlib.md5
    digests = b"".join([md5(key + coord).digest() for coord in _coords(d)])
    # 13 hexadecimal digits are 52 bits
    out = (np.frombuffer(digests, ">u8")[::2] >> 12) / _SCALE
    out.flags.writeable = False
    return out


def worker(seed: int, k: int, t: int, workers: int) -> int:
    """Worker of inner step t of epoch k."""
    return int(uniform(seed, "worker", k, t) * workers)


def pick(seed: int, k: int, steps: int) -> int:
    """Inner step, of 0..steps-1, whose iterate becomes the next anchor."""
    return int(uniform(seed, "pick", k, 0) * steps)


def spark_uniform(key: str) -> str:
    """Spark SQL for the uniform of a string expression `seed|stream|k|t|coord`."""
    return f"(CAST(conv(substring(md5({key}), 1, 13), 16, 10) AS DOUBLE) / {_SCALE!r}D)"


def duck_uniform(key: str) -> str:
    return f"(('0x' || substr(md5({key}), 1, 13))::BIGINT / {_SCALE!r}::DOUBLE)"
