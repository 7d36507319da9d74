"""Shard graph builders: (ids, matrix, R, L, ...) -> neighbour positions, one row per vector, -1 padded, nearest first where order means distance."""

from shardgraph.operators.builders.detour import knn_detour
from shardgraph.operators.builders.hier import knn_hier
from shardgraph.operators.builders.knn import knn_descent, knn_exact
from shardgraph.operators.builders.robust import robust

BUILDERS = {"knn_exact": knn_exact, "knn_descent": knn_descent, "knn_detour": knn_detour, "robust": robust, "knn_hier": knn_hier}
