"""Features, clustering, similarity, matching, likelihood, segments and measures."""
