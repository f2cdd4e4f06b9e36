"""The methods: meshes, bases, geometry, graphs, weights, partitions, subdomains, matrices, solvers, measures."""
