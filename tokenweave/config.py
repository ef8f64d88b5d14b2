"""Parameters of a linkage and their defaults."""

from __future__ import annotations

from dataclasses import dataclass

#: Letters and digits of a word; the ASCII alphabet leaves all others out.
WORD = {"unicode": r"[\p{L}\p{N}]+", "ascii": r"[a-z0-9]+"}
OTHER = {"unicode": r"[^\p{L}\p{N}]", "ascii": r"[^a-z0-9]"}


@dataclass(frozen=True)
class LinkConfig:
    """``k``: a token in more addresses of a list than this is no blocking key there (None: no cut); a pair sets the
    sides apart. ``tau``: threshold on the scale of ``measure``. ``dedup``: distinct, or owner (each pair is kept
    at its smallest shared token, which saves a shuffle of all raw pairs)."""

    k: int | tuple[int | None, int | None] | None = 100
    tau: float | None = None
    measure: str = "pooled"
    blocker: str = "phrases"
    scorer: str = "chars"
    dedup: str = "distinct"
    alphabet: str = "unicode"
    length_filter: bool = False

    @property
    def cuts(self) -> tuple[int | None, int | None]:
        return self.k if isinstance(self.k, tuple) else (self.k, self.k)
