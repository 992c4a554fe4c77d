"""Applications, the exploration loop, and shared storage between steps."""
