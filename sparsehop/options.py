"""Options of products and traversals."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class MatvecOptions:
    """``early_exit`` and ``structure_only`` are on exactly for Boolean OR when left at None; ``mask_strategy`` is how a column product's mask is joined."""

    switch_point: float = 0.01
    early_exit: bool | None = None
    structure_only: bool | None = None
    merge: str = "hash"
    mask_placement: str = "post"
    mask_identity: object = 0
    join_strategy: str = "auto"
    mask_strategy: str = "auto"
    broadcast_bytes: int = 256 << 20

    def __post_init__(self) -> None:
        if not 0 < self.switch_point <= 1:
            raise ValueError("switch_point lies in (0, 1]")
        joins = ("auto", "broadcast", "shuffle_hash", "merge")
        for name, allowed in (("merge", ("hash", "sort", "none")), ("mask_placement", ("post", "pre")), ("join_strategy", joins), ("mask_strategy", joins)):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} is one of {allowed}")


@dataclass(frozen=True)
class BfsOptions:
    """The five switches of the traversal besides the direction rule, which is a plan of its own."""

    mask: bool = True
    early_exit: bool = True
    operand_reuse: bool = True
    structure_only: bool = True
    merge: str = "hash"
    mask_placement: str = "post"
    with_parent: bool = False
    max_depth: int | None = None
    waves: bool = False
    join_strategy: str = "auto"
    broadcast_bytes: int = 256 << 20
