"""The same problems by other methods: flat, vertex-, edge- and block-centric, linear algebra, brute force."""
