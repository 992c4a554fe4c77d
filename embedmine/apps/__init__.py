"""Applications: motifs, cliques, frequent subgraphs, matching, dense subgraphs."""
