"""DataFrame operators of the method: batches, rating, ranking, pruning, proxies, measures."""
