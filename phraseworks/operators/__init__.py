"""Mining, segmentation, topic models, ranking, baselines and measures."""
