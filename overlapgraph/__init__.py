"""Support-overlap graphs of several meshes: partition, assembly, solve and measures on Spark."""
