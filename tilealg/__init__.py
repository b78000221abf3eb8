"""Matrix-product analytics on Spark: tiled and row-broadcast products and the learners built on them."""
