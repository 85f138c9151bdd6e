"""Running plans: threads, reuse of intermediates, measures."""
