"""Streams of edges. The method itself has no streams; these are extensions for users of growing graphs."""
