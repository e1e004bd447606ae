"""strata: k-means over very large point sets by stratified subsets, as DataFrame plans."""
