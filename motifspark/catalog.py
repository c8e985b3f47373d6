"""The motif catalogue and the query groups (fixed values)."""

from __future__ import annotations

from .motif import Motif

MOTIFS = {
    name: Motif.parse(name, text)
    for name, text in {
        "path2": "AB BC",
        "path3": "AB BC CD",
        "tri_cycle": "AB BC CA",
        "tri_ff": "AB BC AC",
        "lollipop": "AB BC CD DB",
        "quad_cycle": "AB BC CD DA",
        "lollipop_ret": "AB BC CD DB BA",
        "pingpong2": "AB BA",
        "pingpong3": "AB BA AB",
        "burst2": "AB AB",
        "out_star3": "AB AC AD",
        "in_star3": "AB CB DB",
        "bifan": "AB CB CD AD",
        "scatter_gather": "AB AC BD CD",
    }.items()
}

GROUPS = {
    "walkthrough": ["tri_cycle", "lollipop", "quad_cycle"],
    "D1": ["path3", "lollipop", "lollipop_ret"],
    "D2": ["path2", "path3", "lollipop", "lollipop_ret"],
    "F1": ["tri_cycle", "tri_ff"],
    "F2": ["tri_cycle", "tri_ff", "path3"],
    "F3": ["tri_cycle", "tri_ff", "path3", "lollipop", "quad_cycle"],
    "C1": ["in_star3", "out_star3", "pingpong3", "tri_cycle"],
    "C2": ["path3", "tri_cycle", "lollipop", "pingpong3", "bifan"],
    "C3": ["path3", "tri_cycle", "tri_ff", "lollipop", "quad_cycle", "lollipop_ret", "pingpong3", "scatter_gather"],
}
#: The eight groups of the experiments; the walkthrough is an example beside them.
EXPERIMENT = ["D1", "D2", "F1", "F2", "F3", "C1", "C2", "C3"]


def group(name: str) -> list[Motif]:
    return [MOTIFS[m] for m in GROUPS[name]]
