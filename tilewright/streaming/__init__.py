"""New objects routed by a static layout, as a stream."""
