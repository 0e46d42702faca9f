"""Plans: whole workloads put together from sources and operators."""
