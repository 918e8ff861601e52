"""Training of feature maps and decoders over many datasets."""
