"""The five training stages and their published row targets."""

# fixed values: rows of each component by stage
STAGES = {
    1: {"image_captions": 350_000_000, "short_video_captions": 4_200_000},
    2: {"image_instructions": 54_000_000, "video_captions_30_180": 3_400_000},
    3: {"retained_instructions": 20_000_000},
    4: {"long_captions": 350_000, "spatial": 4_000_000, "retained_instructions": 40_000_000},
    5: {"converted_streaming": 2_801_360, "existing_streaming": 543_943},
}
