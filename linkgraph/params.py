"""Parameters of the linking methods, in one frozen object."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Params:
    #: "token": a node for every token of a cell; "cell": one for the whole value.
    token_mode: str = "token"
    tau_cid: float = 0.70
    #: Whether an edge needs a similarity of at least the threshold or above it.
    edge_cmp: str = "ge"
    alpha_min: float = 0.3
    alpha_max: float = 0.8
    fixed_alpha: float | None = None
    #: Valid rows at which half of the evidence confidence is reached.
    n0: float = 100.0
    beta: float = 0.5
    eps: float = 1e-9
    #: Denominator of the relative gap: sum of magnitudes, or the signed sum.
    gap_denominator: str = "abs"
    #: "printed": |a-b|**beta / sum; "homogeneous": (|a-b| / sum)**beta.
    gap_form: str = "printed"
    #: Cosine of the padded vectors, or of the slots that both columns have.
    cos_on: str = "padded"
    feature_scale: str = "raw"
    tau_tok: float = 0.85
    merge: bool = True
    merge_numeric: bool = False
    merge_min_length: int = 4
    c_m: float = 0.25
    c_l: float = 0.25
    c_v: float = 0.25
    c_f: float = 0.25
    freq_top: int = 100
    weighted: bool = True
    cid_edges: bool = True
    #: "unit": token edges of a column weigh 1 each; "share": column edges get a fixed mass.
    cid_edge_mass: str = "share"
    cid_share: float = 0.5
    walk_length: int = 20
    walks_per_node: int = 10
    dim: int = 300
    window: int = 3
    #: "ppmi": positive PMI with the shift of one negative sample, 0, hashed to ``dim``; "w2v": skip-gram on parts of the walks; "blocked": skip-gram in blocks.
    learner: str = "ppmi"
    #: Graphs up to this many edges walk on broadcast arrays, larger ones by joins.
    local_edges: int = 4_000_000
    tau_sm: float = 0.2
    tau_er: float = 0.3
    #: Record pairs that are scored: those that share a rare token ("shared"), those whose
    #: vectors agree in a band of hyperplane signs ("lsh"), either ("both"), or "all".
    er_candidates: str = "both"
    #: Largest document frequency of a token that proposes record pairs.
    max_df: int = 50
    #: Cosine at which bands of hyperplane signs meet a pair almost surely.
    er_cosine: float = 0.7
    seed: int = 42

    def __post_init__(self):
        if not 0 <= self.alpha_min <= self.alpha_max <= 1:
            raise ValueError("need 0 <= alpha_min <= alpha_max <= 1")
        weights = (self.c_m, self.c_l, self.c_v, self.c_f)
        if min(weights) < 0 or not sum(weights):
            raise ValueError("importance weights must be >= 0 and not all 0")
        for name, allowed in (("token_mode", ("token", "cell")), ("edge_cmp", ("ge", "gt")), ("gap_denominator", ("abs", "printed")), ("gap_form", ("printed", "homogeneous")), ("cos_on", ("padded", "shared")), ("cid_edge_mass", ("unit", "share")), ("feature_scale", ("raw", "signed_log")), ("learner", ("ppmi", "w2v", "blocked")), ("er_candidates", ("shared", "lsh", "both", "all"))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")

    def tripartite(self) -> Params:
        """The plain graph baseline: no column edges, no merging, uniform walks, whole values."""
        return replace(self, cid_edges=False, merge=False, weighted=False, token_mode="cell")
