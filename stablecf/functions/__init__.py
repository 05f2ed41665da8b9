"""Part of the cluster-feature engine."""
