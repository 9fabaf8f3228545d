"""Event streams of edges."""
