"""Record-level and set-level operators of the conflation pipeline."""
