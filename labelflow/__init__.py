"""Label propagation on changing similarity graphs, as DataFrame plans."""
