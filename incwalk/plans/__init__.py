"""Graph layout, walk stores, updates, personalised walks and exact iterations as plans."""
