"""DataFrame operators of the engine and the operators around it."""
