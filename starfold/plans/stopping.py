"""Stop rules over one step's metric row.

``edge_agreement``: both ends of every edge that entered the step had the same label. Current edges always
connect each component, so labels are then constant on it, and the least vertex never loses its own id.
``quiet_counter``: no propagation left a vertex that is not its own minimum.
``label_pause``: no label was lowered. Unsound, since a label can rest while an edge is being turned; it is
here for the negative test only.
"""

RULES = {
    "edge_agreement": lambda row: row["mismatched"] == 0,
    "quiet_counter": lambda row: row["active"] == 0,
    "label_pause": lambda row: row["lowered"] == 0,
}


def rule(name: str):
    if name not in RULES:
        raise ValueError(f"unknown stop rule {name!r}; one of {sorted(RULES)}")
    return RULES[name]
