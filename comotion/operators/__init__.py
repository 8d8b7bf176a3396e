"""Physical building blocks over samples, segments, clusters and convoys."""
