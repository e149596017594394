"""synthselect: synthesise, score, select and retrain over Spark tables."""
