"""Configuration as files, presets, and the parts of a run found by name."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace
from pathlib import Path


@dataclass(frozen=True)
class Config:
    """Everything that decides a run."""

    log: str = "conv"
    tau: float = 1.0
    max_depth: int = 4
    order: str = "first_index"
    oracle: str | None = None
    remove_existing: bool = False
    composer: str = "threshold"
    delta: float = 0.1
    net_floor: float = 0.5
    schedule: str = "constant"
    heuristic: str | None = None
    strategy: str = "bfs"
    prefer: str = "post"
    cut_mode: str = "paper"
    blacklist: tuple[str, ...] = ()
    batch: int = 256
    max_candidates: int | None = None
    seconds: float | None = 600.0
    post_seconds: float | None = 600.0
    stagnation: int | None = None
    post: tuple[str, ...] = ("lp", "selfloops")
    lp_mode: str = "fit"
    with_universal: bool = True
    supervision: str = "reduced"
    seed: int = 0
    extra: dict = field(default_factory=dict)

    def to_json(self) -> str:
        return json.dumps(asdict(self), indent=1, ensure_ascii=False)

    @staticmethod
    def from_json(text: str) -> Config:
        d = json.loads(text)
        return Config(**{k: tuple(v) if isinstance(v, list) else v for k, v in d.items()})

    def save(self, path: str) -> None:
        Path(path).write_text(self.to_json())

    @staticmethod
    def load(path: str) -> Config:
        return Config.from_json(Path(path).read_text())


PRESETS: dict[str, Config] = {
    "base": Config(),
    "region_implicit": Config(oracle="token_dominance", remove_existing=True),
    "lp_implicit": Config(oracle="lp"),
    "log_language": Config(oracle="log_language", tau=0.8),
    "uniwired": Config(composer="uniwired"),
    "uniwired_lp": Config(composer="uniwired", oracle="lp"),
    "delta": Config(composer="delta", tau=0.5, delta=0.1),
    "delta_growing": Config(composer="delta", tau=0.5, delta=0.1, schedule="linear"),
    "postponing": Config(composer="postponing", heuristic="eventually"),
    "best_first": Config(strategy="best", heuristic="eventually"),
    "depth_first": Config(strategy="dfs"),
    "pre_first": Config(prefer="pre"),
}


def preset(name: str, **changes) -> Config:
    return replace(PRESETS[name], **changes)


class Context:
    """Data that components ask for by name: built on first use, then shared."""

    def __init__(self):
        self._make: dict = {}
        self._have: dict = {}

    def offer(self, name: str, make) -> None:
        self._make[name] = make
        self._have.pop(name, None)

    def get(self, name: str):
        if name not in self._have:
            if name not in self._make:
                raise KeyError(f"nothing offers {name!r}; known: {', '.join(sorted(self._make))}")
            self._have[name] = self._make[name](self)
        return self._have[name]
