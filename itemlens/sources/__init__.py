"""Reading tables, building baskets, writing results."""
