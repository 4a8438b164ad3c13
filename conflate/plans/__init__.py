"""Plan helpers: materialisation, size-checked broadcast, connected components."""
