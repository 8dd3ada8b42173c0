"""graphloom: Spark-native graph analytics (BFS, triangles, PageRank) and its data operators."""
