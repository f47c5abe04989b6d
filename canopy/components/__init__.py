"""Connected components: general graphs and the forest algorithm."""
