"""Front end, workers, dispatch to replicas, and the choice of plan."""
