"""The engines that the multiway engine is compared with."""
