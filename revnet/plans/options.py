"""Options of a batch query, with their checks."""

from __future__ import annotations

from dataclasses import dataclass

RULES = frozenset({"stop", "ancestor", "path_count"})


@dataclass(frozen=True)
class RknnOptions:
    """How a batch is answered; every combination gives the same answers, at different cost.

    ``plan``: flood (labels of the k nearest facilities at every vertex), expand (from the query
    facilities outwards, pruned by ``rules``), region (intervals of edges joined with objects) or
    auto. ``quick`` tests candidates by a circle count before exact kNN. ``share`` keeps what is
    searched for the whole batch; without it every query grows its own k nearest and every
    unresolved pair is searched for itself. ``cache_key`` keys the distance cache by object or by
    vertex (then the lists that the expansion has met are in it already); ``cache_payload`` stores
    kNN lists or whole truncated maps. ``ends`` also tests objects at vertices where a branch
    stops. ``ranks`` adds the rank ``rk`` to the answers, for which every answer needs its list.
    ``ties`` ranks equal distances by id or together. ``exclude_self`` asks for facilities that
    have the query among their k nearest other facilities, in place of objects.
    """

    k: int = 10
    ties: str = "by_id"
    rules: tuple[str, ...] = ("stop",)
    max_radius: int | None = None
    max_hops: int | None = None
    quick: bool = True
    bound: str = "mbc"
    count_mode: str = "exact"
    share: bool = True
    cache_key: str = "vertex"
    cache_payload: str = "knn"
    ends: bool = False
    ranks: bool = False
    exclude_self: bool = False
    plan: str = "auto"
    tree_fanout: int = 16
    leaf_size: int = 32
    max_rounds: int = 10_000

    def __post_init__(self):
        if self.k < 1:
            raise ValueError("k must be at least 1")
        for name, allowed in (
            ("ties", {"by_id", "inclusive"}), ("bound", {"mbr", "mbc", "both"}), ("count_mode", {"exact", "upper"}),
            ("cache_key", {"object", "vertex"}), ("cache_payload", {"knn", "full_map"}), ("plan", {"auto", "flood", "expand", "region"}),
        ):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {sorted(allowed)}")
        if not set(self.rules) <= RULES:
            raise ValueError(f"rules must be among {sorted(RULES)}")
        if self.exclude_self and self.plan not in ("auto", "flood"):
            raise ValueError("exclude_self needs the flood plan: the stop rule does not hold for facilities that are objects")
        if (self.max_radius is not None or self.max_hops is not None) and self.plan in ("flood", "region"):
            raise ValueError("a radius or hop limit needs the expand plan")


#: The stages as first described for one machine: prune by ancestors and stops, key the cache by object.
FAITHFUL = RknnOptions(rules=("stop", "ancestor"), cache_key="object", ends=True, plan="expand")
