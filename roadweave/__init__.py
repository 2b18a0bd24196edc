"""roadweave: Spark-native clustering of network-bound trajectories through bipartite graphs."""
