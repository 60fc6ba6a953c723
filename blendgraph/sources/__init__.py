"""Tables, edge lists and the graphs built from tables."""

from .graphs import bipartite_graph, colink_graph, copurchase_graph, line_graph, planted_content, planted_graph, same_host_graph, shingle_graph, user_key_graph
from .planted_source import PlantedEdges
from .tables import read_edges, read_table, write_cooc, write_model_card, write_vectors, write_word2vec_text

__all__ = [
    "PlantedEdges", "bipartite_graph", "colink_graph", "copurchase_graph", "line_graph", "planted_content", "planted_graph", "read_edges", "read_table",
    "same_host_graph", "shingle_graph", "user_key_graph", "write_cooc", "write_model_card", "write_vectors", "write_word2vec_text",
]
