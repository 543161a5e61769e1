"""The methods that the tile clustering is compared with.

All take points and axis names and return the points with a ``label`` (BIGINT, null for
noise).  Quadratic methods refuse inputs over a stated size instead of running out of
memory; that refusal is what their missing results in a comparison stand for.
"""

from gridhub.baselines.common import BaselineTooLarge
from gridhub.baselines.density import dbscan, dbscan_multi, mean_shift
from gridhub.baselines.hierarchy import birch, linkage, linkage_by_parts, single_linkage, single_linkage_at, ward
from gridhub.baselines.partition import affinity_propagation, gaussian_mixture, kmeans, minibatch_kmeans, power_iteration, spectral
from gridhub.baselines.subspace import clique, clique_units, full_units

__all__ = ["BaselineTooLarge", "affinity_propagation", "birch", "clique", "clique_units", "dbscan", "dbscan_multi", "full_units", "gaussian_mixture", "kmeans", "linkage", "linkage_by_parts", "mean_shift", "minibatch_kmeans", "power_iteration", "single_linkage", "single_linkage_at", "spectral", "ward"]
