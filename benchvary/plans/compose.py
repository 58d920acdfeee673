"""Variant specifications: single edits, the paired grid, stacks, the ladder and the ratio family."""

from __future__ import annotations

from benchvary.operators.edits import RATIO

# Spec rows: variant_id, v1, v2, ratio, l1, l2, l3, l4, n_hard.
IMAGE = ("V1", "V2", "V3")
TEXT = ("L1", "L2", "L3", "L4")
HARD = {"V1", "V3", "L1", "L2", "L4"}


def spec(edits: tuple[str, ...], ratio: float = RATIO, name: str | None = None) -> tuple:
    """A composition of distinct edits as answerers meet it: flags. samples.apply_spec makes the sample itself, in the order given."""
    has = lambda e: int(e in edits)
    return (name or "+".join(edits) or "vanilla", has("V1"), has("V2"), ratio if "V3" in edits else 1.0, *(has(e) for e in TEXT), sum(e in HARD for e in edits))


VANILLA = spec(())
SINGLE_IMAGE = (VANILLA, *(spec((v,)) for v in IMAGE))
SINGLE_TEXT = (VANILLA, *(spec((t,)) for t in TEXT))
GRID = tuple(spec((v, t)) for v in IMAGE for t in TEXT)
HARDEST, EASIEST = spec(("V1", "L4")), spec(("V2", "L3"))
EXTREMES = (HARDEST, VANILLA, EASIEST)
LADDER = (VANILLA, spec(("V1",)), spec(("V1", "V3")), spec(("V1", "V3", "L4")), EASIEST)
RATIOS = (VANILLA, *(spec(("V3",), r, f"V3x{r:.2f}") for r in (1.25, 1.5, 1.75, 2.0)))
EVERYTHING = (*SINGLE_IMAGE, *SINGLE_TEXT[1:], *GRID, *LADDER[2:4])


def all_compositions(max_image: int = 2, max_text: int = 2) -> list[tuple]:
    """Every set of at most so many edits on each side, an object not both added and removed."""
    from itertools import combinations

    sides = [[c for k in range(n + 1) for c in combinations(e, k)] for e, n in ((IMAGE, max_image), (TEXT, max_text))]
    return [spec((*v, *t)) for v in sides[0] for t in sides[1] if not {"V1", "V2"} <= set(v)]
