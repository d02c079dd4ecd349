"""Settings of a corpus run, checked and hashed for the manifest."""

from __future__ import annotations

import dataclasses
import hashlib
import json

A_SOURCES = tuple(f"src{i}" for i in range(1, 13))
B_SOURCES = tuple(f"src{i}" for i in range(13, 20))


@dataclasses.dataclass(frozen=True)
class Config:
    target: str = "en"
    source_order: tuple[str, ...] = (*A_SOURCES, *B_SOURCES, "src0")
    roles: tuple[tuple[str, str], ...] = (*((s, "A") for s in A_SOURCES), *((s, "B") for s in B_SOURCES), ("src0", "seed"))
    seed: int = 0
    key_mode: str = "normalized"
    run_keep: int = 3
    min_words: int = 50
    lid_min_probability: float = 0.5
    shingle_n: int = 3
    k: int = 64
    bands: int = 16
    rows: int = 4
    tau: float = 0.8
    char_n: int = 5
    seed_min_words: int = 200
    drop_percent: int = 15
    split_percent: int = 95
    vocab: int = 16_000
    bootstrap: int = 500

    def __post_init__(self):
        for ok, what in (
            (self.bands * self.rows <= self.k, "bands x rows exceeds the signature"),
            (0 < self.tau <= 1, "tau lies outside (0, 1]"),
            (0 <= self.drop_percent < 100, "drop_percent lies outside [0, 100)"),
            (0 < self.split_percent < 100, "split_percent lies outside (0, 100)"),
            (self.key_mode in ("normalized", "raw"), "key_mode is normalized or raw"),
            (len(set(self.source_order)) == len(self.source_order), "a source comes twice in source_order"),
        ):
            if not ok:
                raise ValueError(what)

    @classmethod
    def load(cls, spark, path: str) -> Config:
        """The settings of a JSON file in any store that Spark reads; settings it doesn't name keep their defaults."""
        given = json.loads("\n".join(r["value"] for r in spark.read.text(path, wholetext=True).collect()))
        unknown = set(given) - {f.name for f in dataclasses.fields(cls)}
        if unknown:
            raise ValueError(f"unknown settings: {', '.join(sorted(unknown))}")
        fixed = lambda v: tuple(fixed(x) for x in v) if isinstance(v, list) else v
        return cls(**{k: fixed(v) for k, v in given.items()})

    def digest(self) -> str:
        return hashlib.sha256(json.dumps(dataclasses.asdict(self), sort_keys=True).encode()).hexdigest()


DEFAULT = Config()
