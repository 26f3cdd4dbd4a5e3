"""Data model: graphs, identifiers, adjacency arrays and tables of the shared folder."""
