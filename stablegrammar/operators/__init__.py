"""Build, merge, passes, expansion, consistency."""
