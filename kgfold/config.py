"""Configuration of an integration run."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace

INVERSE = {"narrower": "broader", "broader": "narrower"}
#: Relations that never make two names one.
NEVER_MERGE = frozenset({"disjointWith"})


@dataclass(frozen=True)
class IntegrationConfig:
    """``classes``: (name, relations) from the strongest to the weakest; the first is the equivalence class."""

    seed: str
    classes: tuple[tuple[str, tuple[str, ...]], ...] = (("equivalence", ("exactMatch", "alignedWith", "replacedBy")), ("reference", ("xref", "approx")))
    order: tuple[str, ...] | None = None
    active_classes: int | None = None  # only the first so many classes are aligned
    targets: str = "all"  # 'all' | 'seed'
    align: bool = True
    obsolete_ambiguous: str = "drop"  # 'drop' | 'least'
    follow_obsolete: bool = False
    obsolete_symmetric: bool = False
    internal_links: str = "all"  # remove 'all' | 'used' | 'keep'
    ambiguous: str = "drop"  # 'drop' | 'least'
    live_targets: bool = False
    canonical: str = "rank"  # 'rank' | 'sink'
    same_source: str = "merge"  # 'merge' | 'edge'
    path: str = "shortest"  # 'shortest' | 'k_shortest' | 'any_anchor'
    k: int = 2
    anchors: str = "seed"  # 'seed' | 'canonical'
    fragment_by: str = "child"  # 'child' | 'both'
    hierarchies: tuple[str, ...] | None = None  # only these vocabularies' edges
    promote_subsumption: bool = False
    extra: dict = field(default_factory=dict, compare=False)

    def __post_init__(self) -> None:
        choices = {"targets": ("all", "seed"), "obsolete_ambiguous": ("drop", "least"), "internal_links": ("all", "used", "keep"), "ambiguous": ("drop", "least"), "canonical": ("rank", "sink"), "same_source": ("merge", "edge"), "path": ("shortest", "k_shortest", "any_anchor"), "anchors": ("seed", "canonical"), "fragment_by": ("child", "both")}
        for name, allowed in choices.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")

    def problems(self) -> list[str]:
        """What is wrong with the configuration itself (data are checked by the expectations)."""
        found = []
        if not self.seed:
            found.append("no seed vocabulary")
        if len(self.classes) < 2:
            found.append("at least two relation classes are needed")
        if self.classes and not self.classes[0][1]:
            found.append("the equivalence class is empty")
        flat = [r for _, rs in self.classes for r in rs]
        found += [f"relation {r} is in two classes" for r in sorted({r for r in flat if flat.count(r) > 1})]
        found += [f"relation {r} may be in no class" for r in flat if r in NEVER_MERGE]
        if self.order and self.order[0] != self.seed and self.seed in self.order:
            found.append("the seed is moved to the first place of the order")
        return found

    def with_(self, **changes) -> IntegrationConfig:
        return replace(self, **changes)

    def relation_rows(self) -> list[tuple[str, str, int]]:
        return [(r, name, rank) for rank, (name, rs) in enumerate(self.classes) for r in rs]

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @staticmethod
    def from_json(text: str) -> IntegrationConfig:
        raw = json.loads(text)
        raw["classes"] = tuple((n, tuple(rs)) for n, rs in raw["classes"])
        for k in ("order", "hierarchies"):
            raw[k] = tuple(raw[k]) if raw.get(k) else None
        return IntegrationConfig(**raw)
