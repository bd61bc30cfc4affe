"""Path queries over grammar-compressed trees, on Spark."""
