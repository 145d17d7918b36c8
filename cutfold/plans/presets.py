"""Named configurations of the multilevel partitioner."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Preset:
    """``initial`` and ``coarsener`` are cluster or matching (or two_hop); ``search``
    is lp, eco or strong; ``cycles`` counts multilevel passes in total."""

    name: str
    coarsener: str = "cluster"
    initial: str = "matching"
    search: str = "eco"
    order: str = "degree"
    cycles: int = 1
    slack: bool = False
    ensemble: bool = False
    active: bool = False
    rounds: int = 10
    stop: float = 0.05
    f: int = 18
    delta: float = 0.03
    tries: int = 5


_BASE = {
    "mi-eco": Preset("mi-eco"),
    "mi-fast": Preset("mi-fast", search="lp"),
    "ci-eco": Preset("ci-eco", initial="cluster"),
    "ci-fast": Preset("ci-fast", initial="cluster", search="lp"),
    "mi-strong": Preset("mi-strong", search="strong", slack=True, ensemble=True),
    "ci-strong": Preset("ci-strong", initial="cluster", search="strong", slack=True, ensemble=True),
}
_FLAGS = {"v": {"cycles": 3}, "b": {"slack": True}, "e": {"ensemble": True}, "a": {"active": True}}
#: The rows of the main comparison, in its order.
COMPARED = [
    "mi-eco-rand", "mi-eco", "mi-eco+v", "mi-eco+v+b", "mi-eco+v+b+e", "mi-eco+v+b+e+a",
    "mi-fast-rand", "mi-fast", "mi-fast+v", "mi-fast+v+b", "mi-fast+v+b+e", "mi-fast+v+b+e+a",
    "ci-fast", "ci-fast+v", "ci-eco+v+b", "mi-strong", "ci-strong",
]
HUGE = ["ci-fast@huge", "ci-fast+v@huge"]


def get(name: str) -> Preset:
    """A preset by name: a base, ``-rand``, flags ``+v +b +e +a``, and ``@huge`` (three
    propagation rounds while coarsening)."""
    body, _, scale = name.partition("@")
    base, *flags = body.split("+")
    random_order = base.endswith("-rand")
    found = _BASE[base.removesuffix("-rand")]
    for flag in flags:
        found = replace(found, **_FLAGS[flag])
    if random_order:
        found = replace(found, order="random")
    if scale == "huge":
        found = replace(found, rounds=3)
    elif scale:
        raise KeyError(name)
    return replace(found, name=name)
