"""Pages written by hand, in layouts that the training generator doesn't make, each with the text a reader would call the article."""

GOLD = [
    (
        """<html><body class="home blog"><div id="masthead"><a href="/"><img src=l.png alt=Logo></a><p>All the news of the valley</p></div>
        <table width=100%><tr><td class="leftnav"><a href=/1>Weather</a><br><a href=/2>Sport</a><br><a href=/3>Farming</a></td>
        <td><div><h2>Bridge reopens after two years</h2><p>The old bridge over the river was reopened on Monday, two years after the flood that carried its middle arch away.</p>
        <p>Work had been held up twice by high water, and the costs rose to <b>four million</b>, most of it paid by the county.</p></div></td></tr></table>
        <div class="footer-links"><a href=/i>Imprint</a> | <a href=/p>Privacy</a></div></body></html>""",
        "Bridge reopens after two years The old bridge over the river was reopened on Monday, two years after the flood that carried its middle arch away. Work had been held up twice by high water, and the costs rose to four million, most of it paid by the county.",
    ),
    (
        """<body><header><nav aria-label=main><ul><li><a href=#>Docs</a><li><a href=#>API</a><li><a href=#>Blog</a></ul></nav></header><main id=main-content><section>
        <h1>Installing the pump</h1><p>Close the valve before you begin. The pump stands on three feet, and all of them must touch the floor.</p>
        <ol><li>Loosen the two screws at the side.<li>Lift the cover and put it aside.<li>Connect the hose.</ol><pre>pump --check --level 3</pre></section></main>
        <aside role=complementary><h4>On this page</h4><ul><li><a href=#a>Valve</a><li><a href=#b>Screws</a></ul></aside></body>""",
        "Installing the pump Close the valve before you begin. The pump stands on three feet, and all of them must touch the floor. Loosen the two screws at the side. Lift the cover and put it aside. Connect the hose. pump --check --level 3",
    ),
    (
        """<div class="navbar"><a href=x>Home</a> <a href=y>Archive</a></div><div>It rained for three weeks that summer, and the fields along the canal stood under water until the middle of August.<br><br>
        My grandmother used to say that the heron had brought it. She had seen him on the weir in May, standing on one leg as if he owned the place, and nobody could tell her otherwise.<br><br>
        We moved the cows to the hill and slept above the stable.</div><div class="footer">Powered by a blog engine</div>""",
        "It rained for three weeks that summer, and the fields along the canal stood under water until the middle of August. My grandmother used to say that the heron had brought it. She had seen him on the weir in May, standing on one leg as if he owned the place, and nobody could tell her otherwise. We moved the cows to the hill and slept above the stable.",
    ),
    (
        """<body><div id="cookieBanner" class="consent-box"><p>We and our partners store information on your device to show you what you like.</p><button>Accept</button></div>
        <article class="entry"><h1>On the mass of light</h1><p>Everyone has seen <math><mi>E</mi><mo>=</mo><mi>m</mi><msup><mi>c</mi><mn>2</mn></msup></math> on a shirt, and few have asked what the letters stand for.</p>
        <figure><svg viewBox="0 0 9 9"><title>hidden</title><path d="M0 0h9"/><text>time axis</text></svg><figcaption>The two clocks drift apart.</figcaption></figure>
        <object data=clock.swf><p>The film of the clocks can be had on request.</p></object>
        <p class="notice-of-terms">The notice of terms that the journal printed in that year was longer than the paper itself.</p></article>
        <section id="comments"><h3>2 comments</h3><article class=comment><p>Very clear, thank you for writing this up so well.</p></article></section></body>""",
        "On the mass of light Everyone has seen E=mc2 on a shirt, and few have asked what the letters stand for. time axis The two clocks drift apart. The film of the clocks can be had on request. The notice of terms that the journal printed in that year was longer than the paper itself.",
    ),
    (
        """<html><body><div class=wrapper><div class="site-top"><ul class="menu"><li><a href=1>Start</a></li><li><a href=2>Shop</a></li></ul></div><div class="post-body">
        <h1>Bread without a machine</h1><p>Mix the flour with water that is only just warm and leave it under a cloth overnight.</p><p style="display:none">keyword bread cheap bread buy bread</p>
        <blockquote>My mother never measured anything, she felt it.</blockquote><p>In the morning add salt &amp; fold the dough four times. <span hidden>track me</span>Bake it in a hot pot.</p>
        <div class="share-buttons"><a href=f>Share</a><a href=t>Post</a></div><form action=/s><label>Your mail</label><input><button>Subscribe</button></form></div>
        <div class="related-posts"><h3>You may also like</h3><ul><li><a href=c>Cakes in ten minutes</a></li></ul></div></div></body></html>""",
        "Bread without a machine Mix the flour with water that is only just warm and leave it under a cloth overnight. My mother never measured anything, she felt it. In the morning add salt & fold the dough four times. Bake it in a hot pot.",
    ),
    (
        """<body><center><font size=2><a href=a.html>prev</a> | <a href=b.html>next</a></font></center><hr><dl><dt>Weir<dd>A low wall across a river, which raises the water above it.<dt>Sluice<dd>A gate in a weir; it is lifted when the river is high.</dl>
        <p id="comment-law">The law on comment was passed in the same year by both chambers, and it has never been changed since then.</p><hr><center><font size=1>&copy; the county</font></center></body>""",
        "Weir A low wall across a river, which raises the water above it. Sluice A gate in a weir; it is lifted when the river is high. The law on comment was passed in the same year by both chambers, and it has never been changed since then.",
    ),
]
