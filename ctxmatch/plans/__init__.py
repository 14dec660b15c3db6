"""Plan builders: schema graphs, join paths, augmented columns, serialization, the matching pipeline and its experiments."""
