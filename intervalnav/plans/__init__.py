"""Choice between search strategies, sharding and the stored layout."""
