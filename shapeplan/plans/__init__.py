"""Planning on the driver: dependency graph, fragments, shape order, filter choices."""
