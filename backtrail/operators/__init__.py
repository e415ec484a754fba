"""Methods over evaluated queries: traces, replay, slices, differences, provenance, measures."""
