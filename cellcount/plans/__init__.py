"""Query model, SQL front end, join patterns, plan trees, workloads and the method chooser (driver side)."""
