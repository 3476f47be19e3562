"""Schema graphs, candidate networks and their compilation."""
