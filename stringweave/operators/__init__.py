"""DataFrame operators of the assembly pipeline."""
