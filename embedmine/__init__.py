"""Mining the subgraphs of one large labelled graph, on Spark."""
