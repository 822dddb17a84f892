"""The runtime model: steps of the method and of the classic way, and their ratio."""

from __future__ import annotations

from dataclasses import dataclass

from .hypergraph import Hypergraph, agm_bound, fhtw, gap_exponent, rho_star


@dataclass
class Sizes:
    """relations, features, longest relation, subspaces, kappa, k, iterations, one-hot width, cells, joined rows."""

    relations: int
    features: int
    longest: int
    subspaces: int
    kappa: int
    k: int
    iterations: int
    width: int
    cells: int
    rows: int


def cost_model(s: Sizes, h: Hypergraph) -> dict[str, float]:
    """Leading terms, without logarithms. lines is the quadratic program's; line_fast that of divide and conquer."""
    n_w = float(s.longest) ** float(fhtw(h))
    out = {
        "marginals": s.relations * s.features**2 * n_w,
        "lines": s.kappa * s.features * float(s.longest) ** 2,
        "lines_fast": s.kappa * s.features * float(s.longest),
        "grid": s.relations * s.features * s.cells * n_w,
        "clustering": (s.cells + s.width) * s.k * s.subspaces * s.iterations,
        "standard_build": s.relations * s.features**2 * n_w + s.width * s.rows,
        "standard_cluster": float(s.iterations) * s.k * s.width * s.rows,
        "agm": agm_bound(h, s.longest),
    }
    out["ours"] = out["marginals"] + out["lines"] + out["grid"] + out["clustering"]
    out["standard"] = out["standard_build"] + out["standard_cluster"]
    out["ratio"] = out["standard"] / out["ours"]
    out |= {"rho_star": float(rho_star(h)), "fhtw": float(fhtw(h)), "gap_exponent": float(gap_exponent(h))}
    return out
