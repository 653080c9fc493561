"""The operators by name, for users who don't want to know which module holds them."""

from ..anonymize.release import anonymised, erdos_renyi, expand, merge_until, relabel, summary
from ..em.points import kmeans, soft_gaussian
from ..hard.fit import fit_rating, fit_simple, local_optimality
from ..hard.score import score_exact, score_plugin, score_table
from ..metrics.graphs import average_path_length, connected_components, global_clustering, sketched_path_length
from ..metrics.privacy import ari, edge_overlap, nmi
from ..soft.predict import dist, exists, hard, mode, soft, top_n
from ..soft.steps import fit_arrow, fit_auto, fit_exact, fit_sampled

__all__ = [
    "anonymised", "ari", "average_path_length", "connected_components", "dist", "edge_overlap", "erdos_renyi", "exists", "expand",
    "fit_arrow", "fit_auto", "fit_exact", "fit_rating", "fit_sampled", "fit_simple", "global_clustering", "hard", "kmeans",
    "local_optimality", "merge_until", "mode", "nmi", "relabel", "score_exact", "score_plugin", "score_table",
    "sketched_path_length", "soft", "soft_gaussian", "summary", "top_n",
]
