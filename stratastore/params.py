"""Parameters of a store."""

from __future__ import annotations

import hashlib
import secrets
from dataclasses import dataclass, field, replace

#: Fixed key of tests and of queries whose tags are compared. ``init_store`` draws a secret one; insertion warns of this one.
TEST_KEY = hashlib.sha256(b"public test key").digest()

#: Schemes by the height their trees are held to; None: as the content's length asks.
HEIGHTS: dict[str, int | None] = {"whole": 0, "fixed": 1, "cdc": 1, "fixed_tree": None, "cdc_tree": None}
SCHEMES = tuple(HEIGHTS)


@dataclass(frozen=True)
class StoreParams:
    """chunk: target size S; ref: size R of a reference, which is the digest's size; window: W of the rolling hash.

    protect: 'hash' (unkeyed digests), 'mac' (keyed tags) or 'siv' (keyed tags and deterministic encryption).
    head: what the window holds at a node's start ('partial': the bytes since then; 'skip': no cut in
    the first W bytes; 'context': bytes before the node too). ring: arithmetic of the rolling hash.
    """

    chunk: int = 256
    scheme: str = "cdc_tree"
    ref: int = 32
    window: int = 48
    head: str = "partial"
    ring: str = "wrap64"
    protect: str = "mac"
    min_len: int | None = None
    max_len: int | None = None
    key: bytes = field(default=TEST_KEY, repr=False)

    def __post_init__(self) -> None:
        if self.scheme not in HEIGHTS:
            raise ValueError(f"unknown scheme {self.scheme!r}")
        if self.chunk < 2 * self.ref:
            raise ValueError("the chunk size must be at least twice the reference size")
        if self.head not in ("partial", "skip", "context") or self.ring not in ("wrap64", "m31") or self.protect not in ("hash", "mac", "siv"):
            raise ValueError("unknown head, ring or protection")
        if not 1 <= self.window <= 4096 or (self.min_len or 0) > (self.max_len or 1 << 62):
            raise ValueError("window or length limits out of range")

    def with_(self, **changes: object) -> StoreParams:
        return replace(self, **changes)  # type: ignore[arg-type]

    @property
    def mac_key(self) -> bytes:
        return hashlib.sha256(b"tag" + self.key).digest()

    @property
    def cipher_key(self) -> bytes:
        return hashlib.sha256(b"cipher" + self.key).digest()

    def lam(self, level: int) -> tuple[int, int]:
        """Expected length of a node at this level, as a fraction."""
        return self.chunk ** (level + 1), self.ref**level

    def fixed_length(self, level: int) -> int:
        a, b = self.lam(level)
        return a // b

    def thresholds(self, limit: int = 1 << 62) -> list[int]:
        """Greatest content length of each height, up to the first that is at least ``limit``."""
        out = [self.chunk]
        while out[-1] < limit:
            out.append(self.fixed_length(len(out)))
        return out

    def height(self, n: int) -> int:
        if (held := HEIGHTS[self.scheme]) is not None:
            return held
        h = 0
        while n * self.ref**h > self.chunk ** (h + 1):
            h += 1
        return h


def init_store(chunk: int = 256, key: bytes | None = None, protect: str = "siv", **options: object) -> StoreParams:
    """Parameters of a new store, sealed if nothing else is asked for, with a fresh secret key if none is given."""
    return StoreParams(chunk=chunk, key=key or secrets.token_bytes(32), protect=protect, **options)  # type: ignore[arg-type]
