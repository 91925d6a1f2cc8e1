"""kgfold: folds overlapping vocabularies of a knowledge graph into one canonical set with a single DAG hierarchy."""
