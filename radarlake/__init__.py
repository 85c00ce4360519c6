"""radarlake: building and analysing corpora of complex radar images, optical tiles and captions on Spark."""
