"""Index building, layouts, retrieval, baselines, measures and relational support operators."""
